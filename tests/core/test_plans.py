import json

import pytest
from pyspark.sql import functions as F

from tabletext.plans import backends, planning
from tabletext.plans.planning import InvalidPlan, Plan, PlanColumn, ReportType
from tabletext.sources import tables
from tabletext.workloads import SOURCES, plan_for


@pytest.mark.parametrize("name", list(SOURCES))
def test_plans_of_all_sources(spark, sf, name):
    plan = plan_for(SOURCES[name](spark, sf), name)
    assert 1 <= len(plan.types) <= 5
    identifiers = [{c.name for c in t.columns if c.role == "identifier"} for t in plan.types]
    assert identifiers[0] and all(i == identifiers[0] for i in identifiers)
    for t in plan.types:  # companions stand next to their metric
        names = t.names()
        assert all(names.index(c.metric) < names.index(c.name) <= names.index(c.metric) + 3 for c in t.columns if c.companion)


def test_validation():
    make = lambda *types: Plan("t", tuple(ReportType(f"r{i}", tuple(PlanColumn(c, "metric") for c in cols)) for i, cols in enumerate(types)))
    assert planning.validate_plan(make("ab", "bc"), list("abc"))
    for plan, options in ((make(), {}), (make(*["a", "b", "c", "ab", "bc", "ac"]), {}), (make("ax"), {}), (make("ab", "ba"), {}), (make("ab", "bc"), {"allow_reuse": False})):
        with pytest.raises(InvalidPlan):
            planning.validate_plan(plan, list("abc"), **options)
    assert [t.names() for t in planning.ensure_identifiers(make("ab", "b"), ["a"]).types] == [["a", "b"], ["a", "b"]]


def test_samples(spark, sf):
    df = tables.order_facts(spark, sf)
    again = [[r["row_id"] for r in planning.sample_rows(df.repartition(n)).collect()] for n in (1, 5)]
    assert again[0] == again[1] and len(again[0]) == 10
    spread = planning.sample_rows(df, 10, "stratified", strata="segment").select("segment").distinct().count()
    assert spread == df.select("segment").distinct().count() and planning.sample_rows(df, 3, "head").count() == 3


def test_fractions_and_top_values(spark, sf):
    df = tables.order_facts(spark, sf)
    shares = {"BUILDING": 1.0, "MACHINERY": 0.5}
    keys = [sorted(r["row_id"] for r in planning.sample_fraction(df.repartition(n), shares, "segment").collect()) for n in (1, 5)]
    n = {r["segment"]: r["count"] for r in df.groupBy("segment").count().collect()}
    assert keys[0] == keys[1] and n["BUILDING"] < len(keys[0]) < n["BUILDING"] + n["MACHINERY"]
    odd = spark.createDataFrame([("x", None), ("x", 1), ("y", 1), (None, 2)], "`a.b` string, c int")
    top = [tuple(r) for r in planning.profile_top(odd, ["a.b", "c"], 1).orderBy("column").collect()]
    assert top == [("a.b", "x", 2, 1), ("c", "1", 2, 1)]
    assert planning.profile_top(odd.limit(0), ["c"]).collect() == []


def test_bounds_of_a_database_read(spark, tmp_path):
    url = f"jdbc:derby:{tmp_path}/db;create=true"
    options = {"url": url, "driver": "org.apache.derby.iapi.jdbc.AutoloadedDriver", "dbtable": "numbers"}
    spark.range(100).write.format("jdbc").options(**options).save()
    df = tables.load_any(spark, "numbers", "jdbc", bounds=("ID", 0, 100, 4), **options)
    assert df.rdd.getNumPartitions() == 4 and df.count() == 100


def test_row_ids_of_equal_rows(spark):
    df = tables.with_row_id(spark.createDataFrame([(1, -0.0), (1, 0.0), (2, 1.5)], "a int, b double"))
    ids = [r["row_id"] for r in df.collect()]
    assert len(set(ids)) == 3 and sum("-2" in i for i in ids) == 1


def fake(calls):
    """An endpoint that fails at first, answers badly for one request, and counts its calls by a file."""

    def call(role, request):
        with open(calls, "a") as f:
            f.write(request + "\n")
        sent = json.loads(request)
        if role == "plan":
            return "oops" if "error" not in sent else json.dumps([{"report_type": "all", "columns": ["order_key", "total_price"]}])
        if sent["n"] == 3:
            return "not json"
        if sent["n"] == 4:
            raise TimeoutError("slow")
        return json.dumps({"doubled": sent["n"] * 2})

    return call


def test_model_calls_are_cached_and_failures_stay_in_their_row(spark, tmp_path):
    log = f"{tmp_path}/calls"
    model = backends.CallableBackend("fake-1", fake(log))
    df = spark.createDataFrame([(i, i % 6) for i in range(24)], "id int, n int")
    for turn in range(2):
        out = backends.CachedCalls(spark, model, f"{tmp_path}/cache").answers(df, "generate", F.to_json(F.struct("n"))).collect()
        assert len(out) == 24 and all(r["cached"] == (bool(turn) and r["n"] not in (3, 4)) for r in out)
        assert {r["n"]: (r["response"], (r["error"] or "")[:12]) for r in out}[5] == ('{"doubled": 10}', "")
        assert all(r["error"] for r in out if r["n"] in (3, 4))
    calls = open(log).read().splitlines()
    assert len(calls) == 4 + 2 * 2 + 2 * 2  # each distinct request once, two of them tried twice, and again by the second run


def test_a_model_may_plan(spark, sf, tmp_path):
    model = backends.CallableBackend("fake-1", fake(f"{tmp_path}/calls"))
    sample = planning.sample_rows(tables.order_facts(spark, sf))
    plan = planning.plan_reports(planning.profile_columns(sample, "order_facts", exact=True), sample, model)
    assert plan.types[0].names() == ["order_key", "total_price"]


def test_rules_leave_no_column_out():
    column = lambda name, kind: {"column": name, "kind": kind, "min": 0, "max": 100}
    text = lambda n: [column(f"label{i}", "categorical") for i in range(n)]
    dates = lambda n: [column(f"day{i}", "temporal") for i in range(n)]
    metrics = [{**column(f"{x}{i}", "numeric"), "max": 1 if x == "rate" else 100} for x in ("price", "n", "rate") for i in range(2)]
    for own in (metrics + text(17), text(45), metrics + dates(3), text(3) + dates(1), metrics + text(40) + dates(20), dates(2)):
        plan = planning.rule_plan("t", [column("key", "identifier"), *own])
        assert 1 <= len(plan.types) <= planning.MOST
        assert {c["column"] for c in own} <= {n for t in plan.types for n in t.names()}
        planning.validate_plan(plan, [c["column"] for c in own] + ["key"])
