import pytest
from pyspark.sql import functions as F

from tabletext.operators import filtering, generation, judging, validation
from tabletext.plans import planning
from tabletext.plans.planning import DECLARED
from tabletext.sources import sinks, tables
from tabletext.workloads import SOURCES


@pytest.fixture(scope="module")
def orders(spark, sf):
    return generation.generate(tables.order_facts(spark, sf).where("order_key < 300"), DECLARED["order_facts"]).cache()


def scores(reports, judges=True):
    return validation.validate(reports, judges)


def plan_text(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", list(SOURCES))
def test_clean_text_is_perfect(spark, sf, name):
    source = SOURCES[name](spark, sf)
    v = scores(generation.generate(source.limit(200) if name == "line_facts" else source, DECLARED[name]))
    bad = v.where("numeric_fp + numeric_fn + temporal_fp + temporal_fn > 0 or judge.factuality < 5 or judge.hallucination < 5 or judge.coherence < 5")
    assert v.count() > 0 and bad.count() == 0


@pytest.mark.parametrize("style", [generation.RenderStyle(date="iso"), generation.RenderStyle(magnitude=True), generation.RenderStyle(wording="paraphrased"), generation.RenderStyle(wording="fixed")])
def test_styles_keep_values(spark, sf, style):
    v = scores(generation.generate(tables.order_facts(spark, sf).limit(150), DECLARED["order_facts"], style), judges=False)
    assert v.where("numeric_fp + numeric_fn + temporal_fp + temporal_fn > 0").count() == 0


def test_damage_costs_what_it_should(orders):
    v = scores(generation.corrupt(orders, F.pmod(F.col("row_id").cast("long"), F.lit(5)))).where("report_type = 'order_value'")
    got = {r["damage"]: tuple(r)[1:] for r in v.groupBy("damage").agg(F.max("numeric_fp"), F.min("numeric_fn"), F.max("temporal_fp"), F.max("judge.factuality"), F.max("judge.hallucination"), F.max("judge.coherence")).collect()}
    assert got == {"none": (0, 0, 0, 5, 5, 5), "within": (0, 0, 0, 5, 5, 5), "drop": (0, 1, 0, 5, 5, 5), "beyond": (1, 1, 0, 2, 2, 5), "stray_year": (0, 0, 1, 5, 3, 5)}


def test_shuffled_sentences_cost_coherence_alone(orders):
    a, b = scores(orders), scores(generation.shuffle_sentences(orders))
    mean = lambda v: v.agg(F.avg("judge.factuality"), F.avg("judge.hallucination"), F.avg("numeric_f1"), F.avg("judge.coherence")).first()
    x, y = mean(a), mean(b)
    assert tuple(x)[:3] == tuple(y)[:3] and y[3] < x[3]


def test_two_rows_in_one_passage_are_found_out(orders):
    assert orders.where(~generation.single_row(F.col("text"))).count() == 0
    assert generation.mix_rows(orders).where(~generation.single_row(F.col("text"))).count() > 100


def test_null_cells_are_in_neither(spark, sf):
    r = generation.generate(tables.order_facts_nulls(spark, sf).where("order_key < 200"), DECLARED["order_facts"])
    v = scores(r)
    assert v.where("numeric_fn + numeric_fp + temporal_fn + temporal_fp > 0").count() == 0
    assert r.where("report_type = 'order_value' and row_id = '77'").first()["text"].count("Its ") == 0


def test_threshold_keeps_subsets(orders):
    v = scores(generation.corrupt(orders), judges=False).cache()
    kept = [{tuple(r) for r in filtering.filter_reports(v, "numeric", t).select("report_type", "row_id").collect()} for t in filtering.TAUS]
    assert all(a <= b for a, b in zip(kept, kept[1:]))
    sweep = [r for r in filtering.tau_sweep(v, "numeric").orderBy(F.desc("tau")).collect()]
    assert [r["n_reports"] for r in sweep[:7]] == [len(k) for k in kept] and sweep[-1]["retained_share"] == 1.0
    means = [r["avg_numeric_p"] for r in sweep if r["n_reports"]]
    assert means == sorted(means, reverse=True)


def test_self_consistency_and_claims(orders):
    damaged = generation.corrupt(orders, F.lit(1))
    claims = judging.claim_table(damaged).where("report_type = 'order_value'")
    assert claims.groupBy("supported").count().orderBy("supported").collect()[0]["count"] * 3 == claims.count()
    verdict = judging.self_consistency(F.lit(5), F.lit(0.5))
    assert not orders.limit(1).select(verdict.alias("x")).first()["x"]


def test_attribution_grounds_a_claim(spark, orders):
    text = F.concat("text", F.lit(" According to the annual filing, sales reached $5 million."))
    assert orders.select(judging.judge_hallucination(text, F.col("cells")).alias("h")).distinct().collect()[0]["h"] == 5
    with pytest.raises(ValueError):
        judging.judge_factuality(text, F.col("cells"), "world")


def test_rows_stay_rows_and_python_stays_out(spark, sf):
    r = generation.generate(tables.order_facts(spark, sf), DECLARED["order_facts"])
    text = plan_text(scores(r))
    assert "Python" not in text and "Pandas" not in text and "Arrow" not in text
    assert text.count("FileScan") == 2 and "hashpartitioning" not in text  # one scan a table; the small side is broadcast
    wide = plan_text(tables.company_facts_wide(spark, sf))
    assert wide.count("hashpartitioning") == 1


def test_the_plan_reads_planned_columns_only(spark, sf):
    one = planning.Plan("part_catalog", (DECLARED["part_catalog"].types[1],))
    assert "p_retailprice" not in plan_text(generation.generate(tables.part_catalog(spark, sf), one))


def test_results_do_not_depend_on_partitions(spark, sf):
    seen = []
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for n in ("1", "7"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        seen.append(sorted(map(tuple, generation.generate(tables.company_facts_wide(spark, sf), DECLARED["company_facts_wide"]).select("row_id", "text").collect())))
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert seen[0] == seen[1]


def test_sinks(spark, orders, tmp_path):
    sinks.write_reports(orders, f"{tmp_path}/r")
    sinks.write_reports(orders.where("report_type = 'order_value'"), f"{tmp_path}/r")
    assert spark.read.parquet(f"{tmp_path}/r").count() == orders.count()
    sinks.release_jsonl(orders, f"{tmp_path}/j")
    row = spark.read.json(f"{tmp_path}/j").where("row_id = '5' and report_type = 'order_value'").first()
    assert row["truth"]["order_key"] == "5" and row["text"].startswith("This report")
    sinks.manifest(spark, f"{tmp_path}/m", "run", tau=0.9)
    assert spark.read.parquet(f"{tmp_path}/m").first()["value"] == "0.9"


def test_one_scan_of_each_table(spark, sf):
    """Sweep and averages read each table once, and need one exchange besides the dealing of small inputs."""
    from tabletext import queries

    for name in ("tau_sweep", "macro_micro_size"):
        text = plan_text(queries.queries()[name](spark, sf))
        assert text.count("FileScan") == 2 and text.count("hashpartitioning") <= 2
    files = spark.read.parquet(f"{sf}/orders.parquet")
    cores = spark.sparkContext.defaultParallelism
    assert tables.spread(files).rdd.getNumPartitions() == cores and tables.spread(spark.range(5)).count() == 5


def test_rubrics_of_a_domain(spark, orders):
    r = orders.withColumn("domain", F.when(F.col("report_type") == "order_value", "finance"))
    bad = generation.corrupt_further(r, F.pmod(F.col("row_id").cast("long"), F.lit(8)))
    both = judging.judge_in_domain(bad, judging.domain_rubric_table(spark)).withColumn("plain", judging.judge(F.col("text"), F.col("cells")))
    got = both.drop("cells").collect()
    for x in got:
        for d in judging.DIMENSIONS:
            if x["domain"] is None or d == "coherence":
                assert x[d] == x["plain"][d]
            else:
                assert x[d] <= x["plain"][d]
    assert any(x[d] < x["plain"][d] for x in got for d in ("factuality", "hallucination"))


def test_reports_are_made_once_and_out_of_the_whole_stage(spark, sf):
    """No filter makes them a second time, and no compiled method holds all of them."""
    plan = generation.generate(tables.part_catalog(spark, sf), DECLARED["part_catalog"])._jdf.queryExecution().executedPlan().toString()
    assert plan.count("This report covers") == len(DECLARED["part_catalog"].types)
    assert not any("Generate" in line and "*(" in line for line in plan.splitlines())


def test_row_ids_take_one_scan(spark, sf):
    plan = tables.with_row_id(tables.load_table(spark, sf, "lineitem"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan") == 1 and plan.count("Exchange") == 1
