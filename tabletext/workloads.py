"""The paper's experiments over the given tables.  Each takes (spark, sf_dir) and options, and returns a frame."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import numeric, temporal
from .operators import extraction, filtering, generation, joins, judging, matching, scoring
from .operators.validation import validate, with_mentions
from .plans import planning
from .plans.planning import DECLARED, Plan
from .sources import tables
from .storage import written

Maker = Callable[[SparkSession, str], DataFrame]

SOURCES: dict[str, Maker] = {
    "order_facts": tables.order_facts, "line_facts": tables.line_facts, "company_facts_wide": tables.company_facts_wide,
    "part_catalog": tables.part_catalog, "customer_place": tables.customer_place, "supplier_place": tables.supplier_place,
}
#: finance: metrics with dates and units; catalog: names and categories
DOMAINS = {"order_facts": "finance", "line_facts": "finance", "company_facts_wide": "finance", "part_catalog": "catalog", "customer_place": "catalog", "supplier_place": "catalog"}


def domain(column: str = "dataset"):
    return F.element_at(F.create_map(*[F.lit(x) for pair in DOMAINS.items() for x in pair]), F.col(column))


def wl_company_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.company_facts_wide(spark, sf_dir)


def wl_small_tables(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables by brand with their rows, and mean columns and rows; personal columns are dropped first."""
    slices = tables.drop_pii_columns(tables.brand_slices(spark, sf_dir), exempt=("table_name",))
    width = len([c for c in slices.columns if c not in ("row_id", "table_name")])
    sizes = slices.groupBy("table_name").agg(F.count("*").alias("n_rows"))
    return sizes.select("table_name", "n_rows", F.lit(width).alias("n_columns"))


def wl_plans(spark: SparkSession, sf_dir: str, mode: str = "grouped") -> DataFrame:
    """A plan from ten sample rows of every source."""
    out = []
    for name, make in SOURCES.items():
        sample = planning.sample_rows(make(spark, sf_dir))
        plan = planning.plan_reports(planning.profile_columns(sample, name, exact=True), sample, mode=mode)
        if mode != "enumerate":
            planning.validate_plan(plan, sample.columns)
        out.append(planning.plan_table(spark, plan))
    return reduce(DataFrame.union, out)


def wl_reports(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(SOURCES), style: generation.RenderStyle = generation.RenderStyle()) -> DataFrame:
    return reduce(DataFrame.union, [generation.generate(SOURCES[n](spark, sf_dir), DECLARED[n], style) for n in names])


def damaged(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(SOURCES)) -> DataFrame:
    """Reports with controlled damage, by a digest of their row modulo 5."""
    return generation.corrupt(wl_reports(spark, sf_dir, names), damage_code())


def damage_code():
    return F.pmod(F.conv(F.substring(F.md5("row_id"), 1, 6), 16, 10).cast("int"), F.lit(5))


def validated(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(SOURCES), judges: bool = False) -> DataFrame:
    return validate(damaged(spark, sf_dir, names), judges)


def wl_judge_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = validated(spark, sf_dir, judges=True).withColumn("domain", domain())
    return scoring.judge_table(v, ["domain"])


def wl_numeric_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scoring.fidelity_table(validated(spark, sf_dir).withColumn("domain", domain()), "numeric", ["domain"])


def wl_temporal_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scoring.fidelity_table(validated(spark, sf_dir).withColumn("domain", domain()), "temporal", ["domain"])


STRAY = " These figures close the fiscal year 2024."


def wl_stray_year(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A year that no cell has: it costs precision, unless coarser mentions of true dates are left out."""
    from .functions import fidelity

    reports = wl_reports(spark, sf_dir, ("company_facts_wide",)).withColumn("text", F.concat("text", F.lit(STRAY)))
    truth, found = temporal.truth_dates(F.col("cells")), temporal.values(temporal.parse_dates(F.col("text")))
    return reports.select("report_type", "row_id", fidelity.match_dates(truth, found).alias("bag"), fidelity.match_dates(truth, found, "granular").alias("granular"))


def wl_tau_sweep(spark: SparkSession, sf_dir: str, on: str = "precision") -> DataFrame:
    """The sweep over all sources of both domains; where a report has no dates, its precision is undefined and passes."""
    return filtering.tau_sweep(validated(spark, sf_dir).withColumn("domain", domain()), "temporal", by="domain", on=on)


def planned(spark: SparkSession, names: tuple[str, ...]) -> DataFrame:
    """The planned column names of each report type of some sources."""
    return reduce(DataFrame.union, [extraction.planned_schema(spark, DECLARED[n]) for n in names])


def sampled(spark: SparkSession, sf_dir: str, names: tuple[str, ...], style: generation.RenderStyle, n: int = 10) -> DataFrame:
    """Reports of ten rows of each source: the rows are chosen before anything is written of them."""
    return reduce(DataFrame.union, [generation.generate(planning.sample_rows(SOURCES[x](spark, sf_dir), n), DECLARED[x], style) for x in names])


def extracted(spark: SparkSession, sf_dir: str, names: tuple[str, ...], oracle: bool = False, wording: str = "paraphrased") -> tuple[DataFrame, DataFrame, DataFrame]:
    """Reports with extracted values, true columns, inferred columns."""
    style = generation.RenderStyle(wording=wording)
    reports, truth = wl_reports(spark, sf_dir, names, style), planned(spark, names)
    schema = truth if oracle else written(extraction.infer_schema(sampled(spark, sf_dir, names, style)), "schema")
    return extraction.extract(reports, schema), truth, schema


def wl_column_table(spark: SparkSession, sf_dir: str, sim: str = "edit", solver: str = "exact") -> DataFrame:
    _, truth, pred = extracted(spark, sf_dir, tuple(SOURCES))
    mapping = matching.match_columns(matching.name_matrix(truth, pred, sim), solver)
    return scoring.score_columns(mapping, truth, pred)


def wl_value_table(spark: SparkSession, sf_dir: str, weighting: str = "value", oracle: bool = False) -> DataFrame:
    found, truth, pred = extracted(spark, sf_dir, tuple(SOURCES), oracle)
    mapping = matching.match_columns(matching.name_matrix(truth, pred))
    return scoring.extraction_table(scoring.score_values(found, mapping, weighting), ["dataset", "report_type"])


def wl_weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ways of averaging, numeric and temporal, by domain: one scan, sums by dataset, the rest from those few rows."""
    return scoring.all_averages(validated(spark, sf_dir).withColumn("domain", domain()), "domain")


def wl_final_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text quality and information fidelity by dataset."""
    names = tuple(SOURCES)
    v = validated(spark, sf_dir, names, judges=True).groupBy("dataset").agg(F.avg("judge.overall").alias("text_quality"))
    found, truth, pred = extracted(spark, sf_dir, names)
    mapping = written(matching.match_columns(matching.name_matrix(truth, pred)), "mapping")
    columns = scoring.score_columns(mapping, truth, pred).groupBy("dataset").agg(F.avg("f1").alias("column_f1"))
    values = scoring.score_values(found, mapping).groupBy("dataset").agg(F.avg("f1").alias("value_f1"))
    out = v.join(columns, "dataset").join(values, "dataset")
    return out.withColumn("information_fidelity", scoring.information_fidelity(F.col("column_f1"), F.col("value_f1")))


def wl_brand_averages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All averages of fidelity over the brand slices, each a dataset of its own."""
    reports = generation.generate(tables.brand_slices(spark, sf_dir), DECLARED["line_facts"])
    v = validate(generation.corrupt(reports, damage_code()), judges=False)
    return scoring.all_averages(v.withColumn("dataset", F.col("table_name")).withColumn("all", F.lit("brands")), "all")


def wl_asymmetry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How much harder extraction is than validation, on the same paraphrased passages of every source."""
    names, style = tuple(SOURCES), generation.RenderStyle(wording="paraphrased")
    found, truth, schema = extracted(spark, sf_dir, names)
    mapping = matching.match_columns(matching.name_matrix(truth, schema))
    return scoring.asymmetry_gap(validate(wl_reports(spark, sf_dir, names, style), judges=False), scoring.score_values(found, mapping))


def wl_plan_ablation(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (5, 10, 20, 50)) -> DataFrame:
    return reduce(DataFrame.union, [planning.plan_stability(SOURCES[n](spark, sf_dir), n, sizes) for n in SOURCES])


def wl_model_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same reports from backends of different style, each validated: mean scores by backend."""
    from .plans.backends import run_grid

    styles = {"long_dates": generation.RenderStyle(), "short_dates": generation.RenderStyle(date="us"), "iso_fixed": generation.RenderStyle(date="iso", wording="fixed"), "magnitudes": generation.RenderStyle(magnitude=True)}
    grid = run_grid(spark, {k: (lambda s=s: validate(wl_reports(spark, sf_dir, ("order_facts",), s), judges=False)) for k, s in styles.items()})
    return grid.groupBy("backend_id").agg(*(F.avg(m).alias(m) for m in ("numeric_p", "numeric_r", "temporal_p", "temporal_r")), F.count("*").alias("n"))


def text_quality_levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, quality as labelled, and 1 where the share of distinct sentences is 0.9 or more."""
    docs, labels = tables.load_table(spark, sf_dir, "documents"), tables.load_table(spark, sf_dir, "labels")
    own = F.split(F.regexp_replace(F.col("text"), r"[.!?\n] *", ".\n"), "\n")
    own = F.filter(own, lambda s: F.length(s) > 1)
    counted = docs.select("doc_id", own.alias("s")).select("doc_id", F.size("s").alias("n"), F.size(F.array_distinct("s")).alias("d"))
    return counted.join(labels, "doc_id").select("doc_id", "quality", (F.col("d") * 10 >= F.col("n") * 9).cast("int").alias("rule"))


def wl_judge_vs_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judging.judge_agreement(text_quality_levels(spark, sf_dir), "rule", "quality")


def wl_messy_mentions(spark: SparkSession, sf_dir: str, kind: str = "documents") -> DataFrame:
    texts = with_mentions(tables.load_texts(spark, sf_dir, kind))
    return texts.select(F.col("id").cast("string").alias("id"), F.size("numbers").alias("n_numbers"), F.size("dates").alias("n_dates"))


def wl_claim_support(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = tables.load_table(spark, sf_dir, "documents"), tables.load_table(spark, sf_dir, "benchmark")
    found = joins.contains_join(docs.select("doc_id", "text"), items.select("item_id", F.col("text").alias("item_text")))
    return found.select("item_id", "doc_id")


def wl_embedding_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greedy token matching between labels; a label's tokens are all its vectors."""
    return matching.match_bags(tables.load_table(spark, sf_dir, "embeddings"), "label", "embedding")


def wl_text_as_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total price by customer, from values extracted out of texts."""
    found, _, _ = extracted(spark, sf_dir, ("order_facts",), oracle=True, wording="varied")
    rows = found.where("report_type = 'order_value'").select(F.col("values")["customer"].alias("customer"), numeric.normalise_number(F.col("values")["total_price"])["value"].alias("price"))
    return rows.groupBy("customer").agg(F.sum("price").cast("decimal(24,2)").alias("total"), F.count("*").alias("n_orders"))


def wl_text_and_keyword(spark: SparkSession, sf_dir: str) -> DataFrame:
    """customer, n_by_value, n_by_keyword: extracted values with that customer, beside passages with the words of its name."""
    found, _, _ = extracted(spark, sf_dir, ("order_facts",), oracle=True, wording="varied")
    named = F.regexp_extract("text", r"\bcustomer (Customer#[0-9]+)", 1)
    both = found.select(F.col("values")["customer"].alias("value"), F.when(named != "", named).alias("word"))
    long = both.select(F.explode(F.array(F.struct(F.col("value").alias("customer"), F.lit(1).alias("v"), F.lit(0).alias("w")), F.struct(F.col("word").alias("customer"), F.lit(0).alias("v"), F.lit(1).alias("w")))).alias("x"))
    return long.select("x.*").where("customer is not null").groupBy("customer").agg(F.sum("v").alias("n_by_value"), F.sum("w").alias("n_by_keyword"))


def wl_corpus_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.corpus_summary(tables.corpus_stats({t: tables.load_table(spark, sf_dir, t) for t in tables.TABLES}))


def plan_for(df: DataFrame, table: str, backend=None) -> Plan:
    """What the planner (rules, or a model) makes of any table, from ten of its rows."""
    sample = planning.sample_rows(df)
    return planning.validate_plan(planning.plan_reports(planning.profile_columns(sample, table, exact=True), sample, backend), df.columns)
