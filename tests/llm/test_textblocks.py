"""Texts that differ are told apart, also those made to make sums over powers of an odd base agree."""

import re

import numpy as np
import pyarrow as pa

from tabletext.llm import decontamination, near_duplicates, search, substring_dedup, suffix_dedup
from tabletext.llm import textblocks as tb


def thue_morse(n: int, a: str, b: str) -> str:
    return "".join((a, b)[i.bit_count() & 1] for i in range(n))


ONE, OTHER = thue_morse(2048, "a", "b"), thue_morse(2048, "b", "a")


def test_hashes_of_slices():
    r = np.random.default_rng(0)
    data = r.integers(97, 99, 3000).astype(np.uint8)
    starts = r.integers(0, 2000, 400)
    ends = starts + r.integers(0, 900, 400)
    hashed = tb.digests(data, starts, ends)
    slices = [data[a:b].tobytes() for a, b in zip(starts, ends, strict=True)]
    assert len(set(hashed.tolist())) == len(set(slices))
    assert {s: h for s, h in zip(slices, hashed.tolist())} == dict(zip(slices, hashed.tolist()))
    for k in (1, 5, 8, 13, 50, 200):
        for values in (data, data.astype(np.uint64)):
            assert len(set(tb.grams(values, k).tolist())) == len({values[i : i + k].tobytes() for i in range(len(values) - k + 1)})
    balanced = np.frombuffer((ONE + OTHER).encode(), np.uint8)
    for n in (512, 1024, 2048):
        one, other = tb.digests(balanced, np.array([0, 2048]), np.array([n, 2048 + n]))
        assert one != other


def test_words():
    text = "Some  wörds\twith " + "x" * 700 + " and\nmore, 日本語 end"
    block = next(tb.blocks(pa.array([text, None, "", "end Some"])))
    words = tb.Words(block)
    own = [block.data[a:b].tobytes().decode() for a, b in zip(words.starts, words.ends)]
    assert own == re.findall(r"[^\x20\x09-\x0D]+", text) + ["end", "Some"]
    assert len(set(words.hashes.tolist())) == len(set(own)) and words.hashes[0] == words.hashes[-1]


def test_long_words_are_not_confused(spark, frame):
    sentence = lambda w: " ".join([w] + [f"w{i}" for i in range(12)])
    docs = frame([ONE, OTHER, sentence(ONE), sentence(OTHER)])
    assert near_duplicates.op8(docs.where("doc_id < 2")).where("kept").count() == 2
    assert substring_dedup.op7(docs).agg({"n_removed": "sum"}).first()[0] == 0
    items = spark.createDataFrame([(1, OTHER)], "item_id long, text string")
    assert [r["doc_id"] for r in decontamination.op10(docs, items).where("contaminated").collect()] == [1, 3]
    asked = spark.createDataFrame([(0, ONE)], "query_id long, query string")
    assert [r["doc_id"] for r in search.search(docs, asked).orderBy("doc_id").collect()] == [0, 2]
    assert suffix_dedup.op6(frame([ONE[:512] + "1", "2" + OTHER[:512]])).count() == 2
