"""A stand-in for a model runs the whole benchmark: every role, one call a distinct request, failures asked again."""

import json

import pytest
from pyspark.sql import functions as F

from tabletext.functions import numeric, temporal
from tabletext.operators import extraction, generation
from tabletext.pipeline import benchmark_table
from tabletext.plans import backends, roles
from tabletext.plans.planning import DECLARED
from tabletext.sources import tables

VALUE = r"([A-Za-z_]+)=([^;]+);"


def endpoint(log, fail=None):
    """Writes cells as ``name=value;`` and reads them again; answers of a role named in ``fail`` time out."""

    def call(role, request):
        import re

        with open(log, "a") as f:
            f.write(json.dumps([role, request]) + "\n")
        if role == fail:
            raise TimeoutError("slow")
        r = json.loads(request)
        if role == "plan":
            return json.dumps([{"report_type": "all", "columns": ["order_key", "customer", "total_price", "order_date"]}])
        if role == "generate":
            return json.dumps({"text": " ".join(f"{c['name']}={c['value']};" for c in r["cells"])})
        if role == "judge":
            good = r["grounding"] == "world" or all(c["value"] in r["text"] for c in r["cells"])
            return json.dumps({"score": 5 if good else 2, "reason": "", "claims": [{"text": r["text"], "supported": good}]})
        if role == "dates":
            return json.dumps([{"value": None, "type": None, "text": m} for m in re.findall(r"[A-Z][a-z]+ \d+, \d{4}", r["text"])])
        if role == "schema":
            return json.dumps({"columns": sorted({n for t in r["texts"] for n, _ in re.findall(VALUE, t)})})
        return json.dumps({n: v for n, v in re.findall(VALUE, r["text"]) if n in r["columns"]})

    return call


@pytest.fixture
def few(spark, sf):
    return tables.order_facts(spark, sf).where("order_key < 40")


def test_the_whole_benchmark_by_a_model(spark, few, tmp_path):
    log = f"{tmp_path}/calls"
    calls = backends.CachedCalls(spark, backends.CallableBackend("stand-in", endpoint(log)), f"file://{tmp_path}/cache")
    n = few.count()
    for turn in range(2):
        b = benchmark_table(spark, few.drop("row_id"), "orders", backend=calls, path=f"file://{tmp_path}/out{turn}")
        v = b.validation.collect()
        assert len(v) == n and all(r["judge"]["overall"] == 5 and r["judge"]["consistent"] for r in v)
        assert all((r["temporal_tp"], r["temporal_fp"], r["temporal_fn"]) == (1, 0, 0) and r["numeric_fn"] == 0 for r in v)
        assert [round(x, 6) for x in b.columns.select("p", "r", "f1").first()] == [1, 1, 1]
        assert {r["r"] for r in b.values.collect()} == {1.0}
        made = [json.loads(x) for x in open(log).read().splitlines()]
        if not turn:
            first = made
    asked = [x for x in first if x[0] != "plan"]
    assert len(asked) == len({tuple(x) for x in asked})
    assert {x[0]: sum(y[0] == x[0] for y in asked) for x in asked} == {"generate": n, "judge": 3 * n, "dates": n, "schema": 1, "extract": n}
    assert [x for x in made[len(first) :] if x[0] != "plan"] == []


def test_judging_by_general_knowledge_shows_no_row(spark, few, tmp_path):
    log = f"{tmp_path}/calls"
    calls = backends.CachedCalls(spark, backends.CallableBackend("stand-in", endpoint(log)), f"file://{tmp_path}/cache")
    reports = generation.generate(few.limit(3), DECLARED["order_facts"])
    found = roles.judge_texts(reports, calls, ("factuality",), grounding="world").collect()
    assert len(found) == 6 and all(r["judge"]["factuality"] == 5 for r in found)
    assert all("cells" not in json.loads(json.loads(x)[1]) for x in open(log).read().splitlines())


def test_failures_are_asked_again_and_temperature_counts(spark, few, tmp_path):
    log, path = f"{tmp_path}/calls", f"file://{tmp_path}/cache"
    reports = generation.generate(few.limit(2), DECLARED["order_facts"]).where("report_type = 'order_value'").drop("text")
    count = lambda: len(open(log).read().splitlines())
    ask = lambda fail, temperature=0.0: roles.write_texts(reports, backends.CachedCalls(spark, backends.CallableBackend("m", endpoint(log, fail), temperature), path)).collect()
    assert all(r["text"] is None and "slow" in r["error"] for r in ask("generate")) and count() == 4
    assert all(r["text"] and r["error"] is None for r in ask(None)) and count() == 6
    assert all(r["text"] for r in ask("generate")) and count() == 6
    ask(None, 0.7)
    assert count() == 8


def test_fallbacks_count_as_bags(spark):
    text = "By 2022 Q4 sales doubled, while by 2022 Q4 costs fell to $5; then $5 again."
    primary = F.array(F.struct(F.lit("2022-12-31").alias("value"), F.lit("date").alias("type"), F.lit("2022 Q4").alias("text")))
    row = spark.range(1).select(
        temporal.values(temporal.parse_dates(F.lit(text), primary)).alias("d"), temporal.values(temporal.parse_dates(F.lit(text))).alias("rules"),
        F.size(numeric.parse_numbers(F.lit(text), tagger=F.array(F.lit("$5"), F.lit("$5"), F.lit("$5"), F.lit("$7")))).alias("n"),
    ).first()
    assert row["d"] == ["2022-12-31", "2022-Q4"] and row["rules"] == ["2022-Q4", "2022-Q4"] and row["n"] == 4


def test_odd_column_names_are_no_patterns(spark):
    rows = [("d", "t", "r", "1", "This report covers id 1. Its price (usd) is $5.00. Its a+b is 7.", ["price_(usd)", "a+b", "price_(eur"])]
    df = spark.createDataFrame(rows, "dataset string, table_name string, report_type string, row_id string, text string, columns array<string>")
    found = extraction.extract(df.drop("columns"), df.select("dataset", "table_name", "report_type", "columns")).first()["values"]
    assert found == {"price_(usd)": "$5.00", "a+b": "7"}


def test_newest_fact_is_one_fact(spark):
    rows = [(1, "x", i, "a") for i in range(20)] + [(1, "x", 5, "z")]
    facts = spark.createDataFrame([(e, a, v, f"p{v}", u, "2024-01-01") for e, a, v, u in rows], "entity int, alias string, value int, period string, unit string, ts string").withColumn("filing_date", F.col("period")).withColumn("concept", F.col("alias"))
    assert tuple(tables.latest_facts(facts.repartition(5), ["entity"]).select("value", "period", "unit").first()) == (19, "p19", "a")
    wide = tables.facts_to_wide(facts.repartition(5), ("x",)).first()
    assert (wide["x_value"], wide["x_period"], wide["x_unit"]) == (19, "p19", "a")
    assert tables.of_form(spark.createDataFrame([("10-K",), ("10-q ",), ("8-K",)], "form string"), ("10-K", "10-Q")).count() == 2


def test_row_ids_tell_rows_apart(spark):
    rows = [("a|b", "c", None), ("a", "b|c", None), ("", None, None), (None, "", None), (None, None, None), ("x", "y", 1e-9), ("x", "y", 2e-9), ("x", "y", 1e-9)]
    ids = [r["row_id"] for r in tables.with_row_id(spark.createDataFrame(rows, "a string, b string, c double")).collect()]
    assert len(set(ids)) == len(rows) and sum(i.endswith("-2") for i in ids) == 1
