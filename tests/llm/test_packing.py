import zlib
from collections import Counter

import numpy as np
from tokenizers import Tokenizer

from tabletext.llm import packing, tokens

from .conftest import corpus


def check(rows, texts, window=1024):
    """Every id in exactly one piece, windows filled without gaps."""
    library = Tokenizer.from_file(tokens.vocabulary_path())
    ids = {i: np.array([*library.encode(t or "", add_special_tokens=False).ids, 0], dtype="<u4") for i, t in enumerate(texts)}
    pieces, windows = {}, {}
    for r in rows:
        own = ids[r["doc_id"]]
        assert r["doc_tokens"] == len(own) and r["length"] > 0
        assert r["ids_crc32"] == zlib.crc32(own[r["start"] : r["start"] + r["length"]].tobytes())
        pieces.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
        windows.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts, ends in ((pieces, {i: len(x) for i, x in ids.items()}), (windows, None)):
        for k, own in parts.items():
            at = 0
            for start, length in sorted(own):
                assert start == at
                at += length
            assert at == ends[k] if ends else at <= window
    assert set(pieces) == set(ids)
    return windows


def test_pieces_cover_all_tokens(frame):
    texts = corpus(n=150) + ["a <|endoftext|> b"]
    windows = check(packing.op2(frame(texts)).collect(), texts)
    full = sum(sum(n for _, n in own) == 1024 for own in windows.values())
    assert full == len(windows) - 1


def test_several_shards(frame):
    texts = corpus(n=100)
    small = packing.pack(frame(texts), shard_tokens=5_000)
    assert len({r["sequence_id"] >> 32 for r in small.select("sequence_id").collect()}) > 3
    ids = small.where("doc_id = 4").orderBy("start").collect()
    library = Tokenizer.from_file(tokens.vocabulary_path())
    assert np.concatenate([np.frombuffer(r["ids"], "<u4") for r in ids]).tolist() == [*library.encode(texts[4]).ids, 0]


def test_neighbours_share_words():
    """Two topics, mixed: windows hold documents of one topic."""
    r = np.random.default_rng(0)
    documents = [np.append(r.integers(1 + 500 * (i % 2), 500 + 500 * (i % 2), 100), 0).astype(np.uint32) for i in range(40)]
    pieces = packing.pack_shard(packing.Bags.of(documents), 505, packing.Statistics.of(documents))
    topics = {}
    for doc, _, _, number, _ in pieces:
        topics.setdefault(number, set()).add(doc % 2)
    assert sum(len(t) == 1 for t in topics.values()) >= len(topics) - 2


def by_brute_force(documents, window, corpus=None):
    """Each window takes the unused document of the highest BM25 score to its seed, by the statistics of the corpus."""
    corpus = documents if corpus is None else corpus
    n, mean = len(corpus), np.mean([len(d) for d in corpus])
    bag = lambda d: dict(zip(*(x.tolist() for x in np.unique(d, return_counts=True)), strict=True))
    df = Counter(t for d in corpus for t in bag(d))
    weights = [{t: np.rint(packing.UNIT * np.log1p((n - df[t] + 0.5) / (df[t] + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len(d) / mean))) for t, tf in bag(d).items()} for d in documents]
    turn = 1 << max(1, len(documents).bit_length())
    unused, order, fill, seed = set(range(len(documents))), [], 0, None
    while unused:
        asked = [t for t in weights[seed] if df[t] > 1] if fill else []
        own = {d: sum(weights[d].get(t, 0) for t in asked) for d in unused}
        best = max(own, key=lambda d: (own[d], -((d - (seed or 0)) % turn)))
        best = best if own[best] > 0 else min(unused)
        unused.remove(best)
        order.append(best)
        if not fill or fill + len(documents[best]) >= window:
            seed = best
        fill = (fill + len(documents[best])) % window
    return order


def test_nearest_of_all_documents():
    """Lists that are too short are made anew: no document is out of reach."""
    r = np.random.default_rng(1)
    documents = [r.choice(40, r.integers(1, 15)).astype(np.uint32) for _ in range(60)]
    want = by_brute_force(documents, 30)
    for k in (1, 3, 64):
        order = [doc for doc, start, *_ in packing.pack_shard(packing.Bags.of(documents), 30, packing.Statistics.of(documents), k) if start == 0]
        assert order == want


def test_shards_use_the_statistics_of_the_corpus(frame):
    """Every seed finds the nearest unused document of its shard, with the frequencies of the whole corpus."""
    r = np.random.default_rng(2)
    words = ["kappa", "sigma", "theta", "omega", "delta", "iota", "rho", "tau", "phi", "chi"]
    texts = [" ".join(r.choice(words, r.integers(3, 11))) for _ in range(60)]
    library = Tokenizer.from_file(tokens.vocabulary_path())
    ids = [np.array([*library.encode(t).ids, 0]) for t in texts]
    statistics = packing.Statistics.of(ids)
    docs = frame(texts)
    digest = {x[0]: x[1] for x in docs.selectExpr("doc_id", "xxhash64(doc_id, text)").collect()}
    for size in (sum(map(len, ids)), 120):
        rows = packing.pack(docs, window=40, shard_tokens=size).where("start = 0").orderBy("sequence_id", "offset").collect()
        shards = {}
        for x in rows:
            shards.setdefault(x["sequence_id"] >> 32, []).append(x["doc_id"])
        assert len(shards) == 1 if size > 120 else len(shards) > 2
        leading = statistics.leading(packing.Bags.of(ids), max(2.0, len(ids) / -(-sum(map(len, ids)) // size))).tolist()
        for own in shards.values():
            order = sorted(own, key=lambda d: (leading[d], digest[d]))
            if sum(len(ids[d]) for d in own) <= size:
                assert own == [order[i] for i in by_brute_force([ids[d] for d in order], 40, ids)]


def test_copies_are_neighbours():
    """Near copies lead with the same tokens, so routing brings them together."""
    r = np.random.default_rng(4)
    bases = [r.choice(2000, 200).astype(np.uint32) for _ in range(100)]
    documents = [b for b in bases] + [np.append(b[:195], r.choice(2000, 5)).astype(np.uint32) for b in bases]
    statistics = packing.Statistics.of(documents)
    keys = statistics.leading(packing.Bags.of(documents), 10)
    assert sum(keys[i][0] == keys[i + 100][0] for i in range(100)) > 80


def test_all_tokens_of_a_seed_count():
    """Long documents: what is shared beyond the weightiest tokens decides too."""
    r = np.random.default_rng(3)
    documents = [r.choice(300, r.integers(80, 160)).astype(np.uint32) for _ in range(40)]
    want = by_brute_force(documents, 200)
    assert [doc for doc, start, *_ in packing.pack_shard(packing.Bags.of(documents), 200, packing.Statistics.of(documents)) if start == 0] == want


def test_empty(frame):
    assert packing.op2(frame([])).count() == 0


def test_ids_of_a_block():
    """Texts that are encoded together, each run of characters once, have the ids that the library gives; so have their rows."""
    import random

    import pyarrow as pa

    from tabletext.llm.textblocks import blocks

    r = random.Random(3)
    parts = ["a", "Bé", "ß", "日本", " ", " ", " ", "　", " ", "\u0085", "\n", ".", ",", "'s", "1", "\t", "\r\n", "\x1c", "\x00", "😀", "the", "̀", "÷"]
    texts = [None, "", " ", "\n", " a", "a ", "a. b, c.\nd", "x <|endoftext|> y"] + ["".join(r.choice(parts) for _ in range(r.randint(0, 40))) for _ in range(600)]
    library, path = Tokenizer.from_file(tokens.vocabulary_path()), tokens.vocabulary_path()
    want = [library.encode(t or "", add_special_tokens=False).ids for t in texts]
    encode = tokens.columns(path)
    for some in (texts, texts[:7] + texts[8:]):  # a special string sends its block the plain way
        for target in (60, 1 << 20):
            got = []
            for block in blocks(pa.array(some, pa.string()), target):
                ids, offsets = encode(block)
                got += [ids[a:b].tolist() for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
            assert got == (want if some is texts else want[:7] + want[8:])
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts), pa.array(range(len(texts)))], names=["doc_id", "text", "digest"])
    rows = [x for b in packing._tokens(path, 0, pa.int64())([batch]) for x in b.to_pylist()]
    assert [packing._wide(pa.scalar(x["ids"])).tolist() for x in rows[:-1]] == [[*w, 0] for w in want]
    for x, w in zip(rows[:-1], want, strict=True):
        assert x["size"] == len(w) + 1
        assert dict(zip(*(packing._wide(pa.scalar(x[c])).tolist() for c in ("terms", "tf")), strict=True)) == Counter([*w, 0])
    df = Counter(t for w in want for t in {*w, 0})
    assert dict(zip(*(np.frombuffer(rows[-1][c], np.int64).tolist() for c in ("terms", "tf")), strict=True)) == df
