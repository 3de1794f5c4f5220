import math
from collections import Counter

import numpy as np

from tabletext.llm import language
from tabletext.llm.textblocks import blocks

import pyarrow as pa


def brute_bits(texts, text, order=language.ORDER):
    """Code length by walking the contexts of every byte."""
    follow = {}
    for t in texts:
        t = bytes(order) + t
        for i in range(order, len(t)):
            for k in range(order + 1):
                follow.setdefault(t[i - k : i], Counter())[t[i]] += 1
    bits, t = 0.0, bytes(order) + text
    for i in range(order, len(t)):
        for k in range(order, -1, -1):
            own = follow.get(t[i - k : i])
            if not own:
                continue
            whole = sum(own.values()) + len(own)
            if t[i] in own:
                bits += math.log2(whole / own[t[i]])
                break
            bits += math.log2(whole / len(own))
        else:
            bits += 8
    return bits


def test_code_lengths_are_exact():
    a, b = [b"the cat sat on the mat", b"the dog"], ["el gato y el perro ñ".encode(), b""]
    model = language.Model(["a", "b"], [language.ContextTree.learn(a), language.ContextTree.learn(b)])
    texts = ["the cat", "", "el ñ", "zzz \U0001f642", "t"]
    scorer = language.Scorer(model)
    for _ in range(2):  # the second time from the table
        got = np.concatenate([scorer.block(x) for x in blocks(pa.array(texts))])
        want = [[brute_bits(a, t.encode()), brute_bits(b, t.encode())] for t in texts]
        assert np.allclose(got, want)


def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = docs.join(language.op5(docs), "doc_id").where("held_out").collect()
    right = [r["lang"] == r["lang_pred"] for r in rows]
    assert len(right) > 150 and sum(right) / len(right) > 0.9


def test_odd_rows(spark, frame):
    docs = frame([None, "", "123 !?", "hello there friend"])
    assert [r["lang_pred"] for r in language.op5(docs).orderBy("doc_id").collect()][:3] == ["und"] * 3
    assert language.op5(frame([])).count() == 0


def test_sample_keeps_every_language(spark):
    """Copies of a hot text, one huge text and a rare language: all are learned, none beyond the bound."""
    rows = [(i, "the same hot text again and again " * 3, "en") for i in range(50)]
    rows += [(100, "ein sehr langer Text " * 40_000, "de"), (101, "unique words here", "xx"), (102, "", "zz"), (103, None, "yy"), (104, "no language", None), (None, "eerste rij", "nl")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    for bound in (40, 2000, 5000, 600_000):
        sample = language.training_sample(docs, train_bytes=bound).collect()
        sizes = Counter()
        for r in sample:
            sizes[r["lang"]] += len(r["text"])
            own = [(t or "").encode() for _, t, x in rows if x == r["lang"]]
            assert any(t.startswith(bytes(r["text"])) for t in own)
        whole = Counter()
        for _, t, x in rows:
            whole[x] += len((t or "").encode())
        assert set(sizes) == {"en", "de", "xx", "nl"}
        assert all(min(bound, 100) <= n <= bound or n == whole[x] for x, n in sizes.items())
        assert language.train(docs, train_bytes=bound).languages == ["de", "en", "nl", "xx"]


def test_prediction_against_brute_force(frame):
    """The least code length wins, and its share of the probabilities is the score."""
    docs = frame([(i, t) for i, t in enumerate(["the cat sat", "a dog sat there", "le chat est assis", "un chien est ici", "el gato", "zzz", "the le"])])
    docs = docs.selectExpr("doc_id", "text", "case when doc_id < 2 then 'en' when doc_id < 4 then 'fr' when doc_id = 4 then 'es' end as lang")
    model = language.train(docs)
    assert model.languages == ["en", "es", "fr"]
    texts = {x: [r["text"].encode() for r in docs.where(f"lang = '{x}'").collect()] for x in model.languages}
    for r in language.identify(docs, model).join(docs, "doc_id").collect():
        bits = [brute_bits(texts[x], r["text"].encode()) for x in model.languages]
        assert r["lang_pred"] == model.languages[int(np.argmin(bits))]
        assert math.isclose(r["score"], 1 / sum(2.0 ** (min(bits) - b) for b in bits), rel_tol=1e-9)
        assert math.isclose(r["bits_per_byte"], min(bits) / len(r["text"].encode()), rel_tol=1e-9)
