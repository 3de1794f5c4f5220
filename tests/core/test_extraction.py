import numpy as np
import pytest
from pyspark.sql import functions as F

from tabletext import pipeline, workloads
from tabletext.operators import extraction, generation, joins, matching, scoring
from tabletext.plans.planning import DECLARED
from tabletext.sources import tables


def test_assignment_against_all_permutations():
    r = np.random.default_rng(3)
    for n, m in [(1, 1), (2, 5), (5, 2), (4, 4), (6, 6), (7, 3)]:
        for _ in range(15):
            gain = np.round(r.random((n, m)), 2)
            pairs = matching.solve_assignment(gain)
            assert len({a for a, _ in pairs}) == len({b for _, b in pairs}) == len(pairs) == min(n, m)
            assert sum(gain[a, b] for a, b in pairs) == pytest.approx(matching.brute_assignment(gain))
    assert matching.solve_assignment(np.zeros((0, 3))) == []


def names(spark, truth, pred):
    make = lambda x: spark.createDataFrame([("d", "t", "r", list(x))], "dataset string, table_name string, report_type string, columns array<string>")
    return make(truth), make(pred)


def test_solvers_in_order_and_permutations(spark):
    truth, pred = ["order_key", "customer", "price", "date"], ["date_of_order", "customers", "price", "keys", "other"]
    totals = {}
    for solver in ("exact", "greedy", "exact_name"):
        for turn in (1, -1):
            m = matching.match_columns(matching.name_matrix(*names(spark, truth[::turn], pred[::turn])), solver)
            totals.setdefault(solver, set()).add(round(sum(r["sim"] for r in m.collect()), 9))
    assert all(len(t) == 1 for t in totals.values())
    assert min(totals["exact"]) >= min(totals["greedy"]) >= min(totals["exact_name"]) == 1.0


def test_equal_names_score_one_and_extra_names_cost_precision(spark):
    def score(truth, pred):
        t, p = names(spark, truth, pred)
        r = scoring.score_columns(matching.match_columns(matching.name_matrix(t, p)), t, p).first()
        return r["p"], r["r"], r["f1"]

    assert score(["a_b", "c"], ["c", "a_b"]) == (1, 1, 1)
    more, fewer = score(["a_b", "c"], ["a_b", "c", "zzzz"]), score(["a_b", "c"], ["c"])
    assert more[1] == 1 and more[0] == pytest.approx(2 / 3) and fewer[0] == 1 and fewer[1] == 0.5


def test_true_schema_extracts_no_worse(spark, sf):
    both = {}
    for oracle in (False, True):
        found, truth, pred = workloads.extracted(spark, sf, ("order_facts",), oracle)
        mapping = matching.match_columns(matching.name_matrix(truth, pred))
        both[oracle] = scoring.score_values(found, mapping).agg(F.avg("r")).first()[0]
    assert 0 < both[False] and 0 < both[True] <= 1
    clean, truth, pred = workloads.extracted(spark, sf, ("order_facts",), True, "varied")
    assert scoring.score_values(clean, matching.match_columns(matching.name_matrix(truth, pred))).agg(F.avg("f1")).first()[0] == 1.0


def test_paraphrases_make_the_task_harder(spark, sf):
    f1 = {}
    for wording in ("varied", "paraphrased"):
        found, truth, pred = workloads.extracted(spark, sf, ("order_facts",), False, wording)
        mapping = matching.match_columns(matching.name_matrix(truth, pred))
        f1[wording] = (scoring.score_columns(mapping, truth, pred).agg(F.avg("f1")).first()[0], scoring.score_values(found, mapping).agg(F.avg("f1")).first()[0])
    assert f1["paraphrased"][0] < f1["varied"][0] == 1.0 and f1["paraphrased"][1] < f1["varied"][1] == 1.0


def test_weightings(spark, sf):
    found, truth, pred = workloads.extracted(spark, sf, ("part_catalog",))
    mapping = matching.match_columns(matching.name_matrix(truth, pred))
    mean = {w: scoring.score_values(found, mapping, w).agg(F.avg("p")).first()[0] for w in ("value", "column_value", "exact")}
    assert mean["exact"] <= mean["value"] and mean["column_value"] <= mean["value"]


def test_malformed_answers(spark):
    df = spark.createDataFrame([(s,) for s in ('{"a": 1}', "{", "[1]", "", None)], "raw_json string")
    assert [r["values"] is not None for r in extraction.with_parsed(df).collect()] == [True, False, False, False, False]


def test_tolerance_join_is_exact(spark):
    a = spark.createDataFrame([(float(x),) for x in (1000, 0, -50, 0.001, 12345.67)], "x double")
    b = spark.createDataFrame([(float(y),) for y in (1000.9, 1001, 1001.1, 999, 998.9, 0, -50.04, 50, 0.001, 12357, 12358.1)], "y double")
    near = lambda r: sorted(map(tuple, r.collect()))
    d = lambda c: F.col(c).cast("decimal(24,6)")
    brute = a.crossJoin(b).where(F.abs(d("x") - d("y")) <= F.abs(d("x")) * F.lit("0.001").cast("decimal(4,3)"))
    assert near(joins.tolerance_join(a, b, "x", "y")) == near(brute)


def test_tolerance_counts_by_brute_force(spark):
    import random

    r = random.Random(5)
    near = lambda: r.choice([0.0, -1.0, 1.0, 1.0]) * round(r.choice([1000, 1001, 5, 0.002]) * r.uniform(0.998, 1.002), 6)
    x, y = [(i, near()) for i in range(120)], [(i, near()) for i in range(150)]
    a, b = spark.createDataFrame(x, "a long, x double"), spark.createDataFrame(y, "b long, y double")
    pairs = joins.tolerance_join(a, b, "x", "y").groupBy("a").agg(F.count("*").alias("n"), F.min("b").alias("least"))
    got = sorted(map(tuple, joins.tolerance_counts(a, b, "x", "y", "a", "b").collect()))
    assert got == sorted(map(tuple, pairs.collect()))
    whole = lambda v: round(v * 10**6)
    brute = {i: [j for j, w in y if 1000 * abs(whole(v) - whole(w)) <= abs(whole(v))] for i, v in x}
    assert got == sorted((i, len(own), min(own)) for i, own in brute.items() if own)


def test_tolerance_join_query_takes_all_orders(spark, sf):
    from tabletext import queries

    o = [(r[0], round(float(r[1]) * 10**6)) for r in tables.load_table(spark, sf, "orders").select("o_orderkey", "o_totalprice").collect()]
    li = tables.load_table(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.max("l_extendedprice"))
    p = [(r[0], round(float(r[1]) * 10**6)) for r in li.collect()]
    brute = {i: [j for j, w in p if 1000 * abs(v - w) <= abs(v)] for i, v in o}
    got = sorted((r["a"], r["n"], r["least"]) for r in queries.queries()["tolerance_join"](spark, sf).collect())
    assert got == sorted((i, len(own), min(own)) for i, own in brute.items() if own)


def test_containment_by_both_ways(spark):
    docs = spark.createDataFrame([(1, "so one two three four five end"), (2, "two three"), (3, "x one two three four five")], "doc_id int, text string")
    items = spark.createDataFrame([(9, "one two three four five"), (8, "two three")], "item_id int, item_text string")
    got = [sorted((r["doc_id"], r["item_id"]) for r in joins.contains_join(docs, items.where("item_id = 9"), m).collect()) for m in (1000, 1)]
    assert got[0] == got[1] == [(1, 9), (3, 9)]


def test_containment_is_the_same_beyond_the_bound(spark):
    texts = ["\none two three four, five", "(one two three four five)", "xone two three four.", "two three, and", "two three", "two three", None, ""]
    docs = spark.createDataFrame([(i // 2, t) for i, t in enumerate(texts)] + [(9, "two three")] * 2, "doc_id int, text string")
    items = spark.createDataFrame([(1, "one two three four"), (2, "one two three four five"), (3, "two three"), (4, "four"), (4, "four"), (5, None)], "item_id int, item_text string")
    small, parts = (sorted((r["doc_id"], r["item_id"]) for r in joins.contains_join(docs, items, m).collect()) for m in (1000, 20))
    assert parts == small and len(small) == len(docs.crossJoin(items).where("contains(text, item_text)").collect())


def test_bags_hold_all_vectors_of_a_label(spark, sf):
    import numpy as np

    from tabletext import queries

    bags = {}
    for r in tables.load_table(spark, sf, "embeddings").collect():
        v = np.array(r["embedding"], float)
        bags.setdefault(r["label"], []).append(v / np.linalg.norm(v))
    want = {}
    for a, b in ((a, b) for a in bags for b in bags if a < b):
        c = np.array(bags[a]) @ np.array(bags[b]).T
        p, q = c.max(axis=1).mean(), c.max(axis=0).mean()
        want[a, b] = 2 * p * q / (p + q)
    for got in (queries.queries()["embedding_token_match"](spark, sf).collect(), matching.match_bags(tables.load_table(spark, sf, "embeddings"), "label", "embedding", 7).collect()):
        assert {(r["label_a"], r["label_b"]) for r in got} == set(want)
        assert all(abs(float(r["score"]) - want[r["label_a"], r["label_b"]]) < 1e-4 for r in got)


def test_experiments_take_all_tables(spark, monkeypatch):
    class Taken(Exception):
        pass

    def taken(spark, sf_dir, names=tuple(workloads.SOURCES), *_):
        raise Taken(*names)

    monkeypatch.setattr(workloads, "wl_reports", taken)
    for f in (workloads.wl_column_table, workloads.wl_value_table, workloads.wl_final_scores, workloads.wl_judge_table):
        with pytest.raises(Taken) as e:
            f(None, "")
        assert set(e.value.args) == set(workloads.SOURCES)


def test_any_table_end_to_end(spark, sf, tmp_path):
    df = tables.load_table(spark, sf, "supplier").select("s_suppkey", "s_name", F.col("s_acctbal").cast("decimal(24,6)").alias("s_acctbal_amount"))
    b = pipeline.benchmark_table(spark, df, "supplier", path=str(tmp_path))
    assert b.validation.where("numeric_fp + numeric_fn > 0").count() == 0 and b.retained.count() == b.reports.count()
    assert b.columns.agg(F.min("f1")).first()[0] > 0.9 and b.values.agg(F.avg("f1")).first()[0] > 0.9
    assert generation.build_prompt(F.col("cells")) is not None and DECLARED


def test_averages_agree(spark, sf):
    v = workloads.validated(spark, sf, ("order_facts", "part_catalog")).withColumn("domain", workloads.domain()).cache()
    fast = {(r["domain"], r["kind"], r["averaging"]): r for r in scoring.all_averages(v, "domain").collect()}
    for kind in ("numeric", "temporal"):
        for how in ("macro", "micro", "size_weighted", "dataset_mean"):
            for r in scoring.average(v, ["domain"], how, kind).collect():
                for m in ("p", "r", "f1"):
                    x, y = fast[r["domain"], kind, how][m], r[m]
                    assert x == y or x == pytest.approx(y)
