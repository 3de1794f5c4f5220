import corpus_pipeline as p

from .conftest import corpus
from .test_decontamination import brute as brute_hits
from .test_near_duplicates import brute as brute_groups
from .test_repeats import brute_bytes


def test_stages_on_their_own_input(spark, frame, tmp_path):
    item = "one two three four five six seven eight nine ten eleven"
    texts = corpus(n=40) + ["1234 !!", f"before {item} after", "kept clean text of its own"]
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, sf = frame(texts), str(tmp_path)

    kept = p.language_id(spark, docs, sf)
    assert kept.columns == docs.columns
    assert {r["doc_id"] for r in kept.collect()} == {i for i, t in enumerate(texts) if t and any(c.isalpha() for c in t)}

    groups = brute_groups(texts, 5)
    assert {r["doc_id"] for r in p.near_dedup(spark, docs, sf).collect()} == {i for i, (_, c) in groups.items() if i == c}

    cut = {r["doc_id"]: r for r in p.suffix_array_dedup(spark, docs, sf).collect()}
    for i, size, removed, _, _ in brute_bytes(list(enumerate(texts)), 200):
        left = cut[i]["text"]
        assert (left is None and texts[i] is None) or size - removed - 4 <= len(left.encode()) <= size - removed

    hits = brute_hits(texts, [(1, item)])
    assert {r["doc_id"] for r in p.benchmark_decontamination(spark, docs, sf).collect()} == {i for i, h in hits.items() if not h[4]}
    assert {r["doc_id"] for r in p.pack_windows(spark, docs, sf).collect()} == set(range(len(texts)))


def test_run_and_extra_columns(spark, sf):
    out = p.run(spark, sf)
    assert out.count() > 100 and "sequence_id" in out.columns
    docs = spark.read.parquet(f"{sf}/documents.parquet").selectExpr("*", "1 as score", "2 as starts", "'x' as node", "3 as shard", "4 as n_words")
    for name, stage in p.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == docs.columns, name
