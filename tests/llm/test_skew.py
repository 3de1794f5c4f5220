from functools import partial

import pytest

from tabletext.llm import anchors, skew, suffix_dedup

from .conftest import corpus


def test_heavy_keys(spark):
    rows = [(i if i % 3 else -1,) for i in range(9000)] + [(None,)] * 5
    table = spark.createDataFrame(rows, "k long").repartition(3)
    assert [r.k for r in skew.heavy_keys(table, "k", len(rows), 100).collect()] == [-1]
    assert skew.heavy_keys(table.where("k > 0"), "k", 6000, 100).count() == 0
    assert skew.heavy_keys(table.limit(0), "k", 0).count() == 0


@pytest.mark.parametrize("ordered", [False, True])
def test_heavy_grams_give_the_same_marks(spark, frame, monkeypatch, ordered):
    texts = list(enumerate(corpus(n=60))) + [(100 + i, "a passage that many documents have, " * 3) for i in range(40)] + [(200, "seen twice " * 9)] * 2
    docs, keys = anchors.keys_of(frame(texts).select("doc_id", "text"))
    table = anchors.anchor_table(docs, suffix_dedup.units(40), keys)

    def marks(df):
        return sorted({(*(r[k] for k in keys), r.place, r.gram, r.region, r.covered, r.several) for r in df.collect()})

    def chosen(df):
        return sorted((r.gram, r.region, r["__id"], r.place) for r in df.where("chosen").collect())

    plain = anchors._repeated_here(table, keys, ordered)
    for shares in (4, 50, 5000):
        monkeypatch.setattr(anchors, "SHARES", shares)
        monkeypatch.setattr(anchors, "heavy_keys", partial(skew.heavy_keys, shares=shares))
        got = anchors.repeated(table, keys, ordered)
        assert marks(got) == marks(plain) and chosen(got) == chosen(plain)
