"""Queries of the library over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import oracles
from . import workloads as wl
from .functions import fidelity, numeric, similarity, temporal
from .operators import extraction, filtering, generation, joins, judging, matching, scoring
from .operators.validation import METRICS, validate
from .plans import planning
from .plans.planning import DECLARED
from .sources import tables

Query = Callable[[SparkSession, str], DataFrame]
_all: dict[str, Query] = {}


def query(f: Query) -> Query:
    _all[f.__name__.removeprefix("q_")] = f
    return f


def exact(c: Column | str) -> Column:
    """Ratios as decimals, which engines print alike."""
    return (F.col(c) if isinstance(c, str) else c).cast("decimal(18,6)")


def flat(v: DataFrame, field: str, *keys: str) -> DataFrame:
    s = F.col(field)
    return v.select(*keys, *(s[x].alias(x) for x in ("tp", "fp", "fn")), *(exact(s[x]).alias(x) for x in ("p", "r", "f1")))


def orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return generation.generate(tables.order_facts(spark, sf_dir), DECLARED["order_facts"])


def damaged_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order reports, damaged by their key modulo 5."""
    return generation.corrupt(orders(spark, sf_dir), F.pmod(F.col("row_id").cast("long"), F.lit(5)))


def damaged_further(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order reports with all kinds of damage, by their key modulo 8."""
    return generation.corrupt_further(orders(spark, sf_dir), F.pmod(F.col("row_id").cast("long"), F.lit(8)))


def scored_orders(spark: SparkSession, sf_dir: str, judges: bool = False) -> DataFrame:
    return validate(damaged_orders(spark, sf_dir), judges)


# --- sources ---


@query
def q_facts_latest(spark, sf_dir):
    facts = tables.facts_long(tables.load_table(spark, sf_dir, "events"))
    return tables.latest_facts(facts, ["entity", "alias"]).select("entity", "alias", "value", "period", "filing_date", "unit")


@query
def q_facts_wide(spark, sf_dir):
    return tables.company_facts_wide(spark, sf_dir).drop("row_id")


@query
def q_facts_alias_coalesce(spark, sf_dir):
    facts = tables.facts_long(tables.load_table(spark, sf_dir, "events")).where("alias <> 'signup' or entity % 3 <> 0")
    wide = facts.groupBy("entity").agg(*(F.max_by("value", F.when(F.col("alias") == a, F.col("ts"))).alias(a) for a in ("signup", "purchase")))
    return tables.coalesce_aliases(wide, {"revenue": ["signup", "purchase"]})


@query
def q_facts_periodized(spark, sf_dir):
    facts = tables.canonical_concepts(tables.facts_long(tables.load_table(spark, sf_dir, "events")), tables.ALIASES)
    both = [tables.periodize(facts, k).groupBy("concept", "span").agg(F.count("*").alias("n"), F.sum("value").cast("decimal(24,6)").alias("total")) for k in ("year", "quarter")]
    return both[0].union(both[1])


@query
def q_pii_columns_flagged(spark, sf_dir):
    out = None
    for t in ("customer", "documents", "conversations"):
        found = tables.pii_columns(tables.load_table(spark, sf_dir, t)).select(F.lit(t).alias("table_name"), "column", "by_name", exact("hit_rate").alias("hit_rate"), "flagged")
        out = found if out is None else out.union(found)
    return out


@query
def q_corpus_stats(spark, sf_dir):
    return tables.corpus_stats({t: tables.load_table(spark, sf_dir, t) for t in tables.TABLES})


@query
def q_small_tables(spark, sf_dir):
    return wl.wl_small_tables(spark, sf_dir)


@query
def q_row_id_lineitem(spark, sf_dir):
    return tables.with_row_id(tables.load_table(spark, sf_dir, "lineitem")).select("l_orderkey", "l_linenumber", "row_id")


@query
def q_asof_fact(spark, sf_dir):
    facts = tables.facts_long(tables.load_table(spark, sf_dir, "events"))
    at = facts.select("entity").distinct().withColumn("at", F.lit("2024-01-15 00:00:00").cast("timestamp_ntz"))
    return tables.asof_facts(facts, at, ["entity"]).select("entity", "value")


# --- planning ---


@query
def q_sample_ten_orders(spark, sf_dir):
    return planning.sample_rows(tables.order_facts(spark, sf_dir)).select("row_id", "customer", "total_price", "order_date")


@query
def q_profile_part(spark, sf_dir):
    return planning.profile_columns(tables.part_catalog(spark, sf_dir), "part_catalog", exact=True).withColumns({"mean": exact("mean"), "avg_len": exact("avg_len")})


@query
def q_profile_orders(spark, sf_dir):
    return planning.profile_columns(tables.order_facts(spark, sf_dir), "order_facts", exact=True).withColumns({"mean": exact("mean"), "avg_len": exact("avg_len")})


def _plan(spark, sf_dir, name, mode="grouped"):
    sample = planning.sample_rows(wl.SOURCES[name](spark, sf_dir))
    return planning.plan_table(spark, planning.plan_reports(planning.profile_columns(sample, name, exact=True), sample, mode=mode))


@query
def q_plan_orders(spark, sf_dir):
    return _plan(spark, sf_dir, "order_facts").select("report_type", "position", "column", "role")


@query
def q_plan_events_wide(spark, sf_dir):
    return _plan(spark, sf_dir, "company_facts_wide").select("report_type", "position", "column", "role", "metric", "companion")


@query
def q_plans_single_type(spark, sf_dir):
    return _plan(spark, sf_dir, "part_catalog", "single_type").select("report_type", "position", "column", "role")


@query
def q_plans_enumerated(spark, sf_dir):
    return _plan(spark, sf_dir, "part_catalog", "enumerate").select("report_type", "position", "column", "role")


@query
def q_plan_stability(spark, sf_dir):
    return wl.wl_plan_ablation(spark, sf_dir).withColumn("similarity", exact("similarity"))


@query
def q_plans_all(spark, sf_dir):
    return wl.wl_plans(spark, sf_dir)


# --- generation ---


@query
def q_reports_orders(spark, sf_dir):
    return orders(spark, sf_dir).select("report_type", "row_id", "text")


@query
def q_reports_nulls(spark, sf_dir):
    return generation.generate(tables.order_facts_nulls(spark, sf_dir), DECLARED["order_facts"]).select("report_type", "row_id", "text")


@query
def q_reports_part(spark, sf_dir):
    return generation.generate(tables.part_catalog(spark, sf_dir), DECLARED["part_catalog"]).select("report_type", "row_id", "text")


@query
def q_reports_events(spark, sf_dir):
    return generation.generate(tables.company_facts_wide(spark, sf_dir), DECLARED["company_facts_wide"]).select("report_type", "row_id", "text")


@query
def q_reports_lines(spark, sf_dir):
    return generation.generate(tables.line_facts(spark, sf_dir), DECLARED["line_facts"]).select("row_id", "text")


@query
def q_reports_template(spark, sf_dir):
    return generation.generate(tables.part_catalog(spark, sf_dir), DECLARED["part_catalog"], generation.RenderStyle(wording="fixed")).select("report_type", "row_id", "text")


@query
def q_reports_corrupted(spark, sf_dir):
    return damaged_orders(spark, sf_dir).select("report_type", "row_id", "damage", "text")


@query
def q_report_cells(spark, sf_dir):
    return generation.project_cells(tables.part_catalog(spark, sf_dir), DECLARED["part_catalog"]).select("report_type", "row_id", F.inline("cells")).select("report_type", "row_id", "name", "kind", "surface", "num")


# --- numbers ---


@query
def q_numbers_in_reports(spark, sf_dir):
    r = generation.generate(tables.line_facts(spark, sf_dir), DECLARED["line_facts"])
    return r.select("row_id", F.posexplode(numeric.parse_numbers(F.col("text"))).alias("pos", "m")).select("row_id", "pos", "m.value", "m.unit")


@query
def q_numbers_in_documents(spark, sf_dir):
    d = tables.spread(tables.load_table(spark, sf_dir, "documents"))
    return d.select("doc_id", F.size(numeric.parse_numbers(F.col("text"))).alias("n_numbers"))


@query
def q_numbers_masked(spark, sf_dir):
    return orders(spark, sf_dir).select("report_type", "row_id", numeric.mask_non_numeric(F.col("text")).alias("masked"))


def _numeric(spark, sf_dir, mode):
    r = damaged_further(spark, sf_dir)
    found = fidelity.match_numbers(numeric.truth_numbers(F.col("cells")), numeric.values(numeric.parse_numbers(F.col("text"))), mode)
    return flat(r.select("report_type", "row_id", found.alias("m")), "m", "report_type", "row_id")


@query
def q_numeric_fidelity_bag(spark, sf_dir):
    return _numeric(spark, sf_dir, "bag")


@query
def q_numeric_fidelity_set(spark, sf_dir):
    return _numeric(spark, sf_dir, "set")


@query
def q_numeric_fidelity_occurrence(spark, sf_dir):
    return _numeric(spark, sf_dir, "occurrence")


@query
def q_numeric_tolerance_edges(spark, sf_dir):
    rows = [(t, f) for t, f in oracles.EDGES]
    df = spark.createDataFrame(rows, "truth string, found string").select(F.col("truth").cast("decimal(24,6)").alias("truth"), F.col("found").cast("decimal(24,6)").alias("found"))
    return df.select("truth", "found", fidelity.within(F.col("truth"), F.col("found")).alias("inside"))


@query
def q_numeric_duplicates(spark, sf_dir):
    df = spark.createDataFrame([(m,) for m in ("bag", "set", "occurrence")], "mode string")
    a = lambda *x: F.array(*(F.lit(v).cast("decimal(24,6)") for v in x))
    m = F.when(F.col("mode") == "bag", fidelity.match_numbers(a(5, 5), a(5), "bag")).when(F.col("mode") == "set", fidelity.match_numbers(a(5, 5), a(5), "set")).otherwise(fidelity.match_numbers(a(5, 5), a(5), "occurrence"))
    return df.select("mode", m.alias("m")).select("mode", "m.tp", "m.fp", "m.fn")


@query
def q_numeric_surfaces(spark, sf_dir):
    df = spark.createDataFrame([(s,) for s in oracles.SURFACES], "surface string")
    n = numeric.normalise_number(F.col("surface"))
    return df.select("surface", n["value"].alias("value"), n["unit"].alias("unit"))


@query
def q_numeric_units(spark, sf_dir):
    r = generation.generate(tables.line_facts(spark, sf_dir), DECLARED["line_facts"])
    found = F.transform(numeric.parse_numbers(F.col("text")), lambda m: F.struct(m["value"].alias("value"), m["unit"].alias("unit")))
    m = fidelity.match_numbers(numeric.truth_units(F.col("cells")), found, units=True)
    return r.select("row_id", m.alias("m")).select("row_id", "m.tp", "m.fp", "m.fn")


@query
def q_cell_coverage(spark, sf_dir):
    r = damaged_orders(spark, sf_dir)
    c = fidelity.cell_coverage(F.col("cells"), F.col("text"), numeric.values(numeric.parse_numbers(F.col("text"))), temporal.values(temporal.parse_dates(F.col("text"))))
    return r.select("report_type", "row_id", exact(c).alias("coverage"))


@query
def q_surface_overlap(spark, sf_dir):
    r = generation.generate(tables.part_catalog(spark, sf_dir), DECLARED["part_catalog"])
    return r.select("report_type", "row_id", exact(fidelity.surface_overlap(F.col("cells"), F.col("text"))).alias("overlap"))


# --- dates ---


@query
def q_dates_in_reports(spark, sf_dir):
    r = generation.generate(tables.company_facts_wide(spark, sf_dir), DECLARED["company_facts_wide"])
    return r.select("report_type", "row_id", F.posexplode(temporal.parse_dates(F.col("text"))).alias("pos", "m")).select("report_type", "row_id", "pos", "m.value", "m.type")


@query
def q_dates_forms(spark, sf_dir):
    """Dates of orders, written in one of fifteen forms by the key."""
    o = tables.load_table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").cast("date").alias("d"))
    f = lambda form: F.date_format("d", form)
    quarter, nth = F.quarter("d").cast("string"), lambda *names: F.element_at(F.array(*map(F.lit, names)), F.quarter("d"))
    forms = [
        F.concat(nth("first", "second", "third", "fourth"), F.lit(" quarter of "), f("yyyy")), F.concat(f("yyyy"), F.lit(" Q"), quarter), F.concat(F.lit("Q"), quarter, F.lit(" "), f("yyyy")),
        F.concat(nth("1st", "2nd", "3rd", "4th"), F.lit(" quarter of "), f("yyyy")), f("yyyy-MM-dd"), f("M/d/yy"), f("MM/dd/yyyy"), f("MMMM d, yyyy"), f("d MMMM yyyy"), f("MMMM yyyy"), F.concat(F.lit("fiscal year "), f("yyyy")),
        F.concat(F.lit("since 1998 and in "), f("yyyy")), F.concat(F.lit("Customer#000002010 paid "), f("yyyy")), F.concat(F.lit("on "), f("MM/dd/yy"), F.lit(" and "), f("MM/dd/yy")), F.lit("none"),
    ]
    surface = F.element_at(F.array(*forms), (F.col("o_orderkey") % len(forms) + 1).cast("int"))
    return tables.spread(o).select("o_orderkey", surface.alias("surface")).select("o_orderkey", "surface", F.array_join(temporal.values(temporal.parse_dates(F.col("surface"))), ",").alias("found"))


@query
def q_dates_relative(spark, sf_dir):
    """Phrases that are counted from the date of an order, one of four by its key."""
    o = tables.load_table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").cast("date").alias("d"))
    said = F.array(*map(F.lit, ("It rose in the following quarter.", "and the following year was flat.", "It fell in the following month.", "none")))
    df = tables.spread(o).select("o_orderkey", "d", F.element_at(said, (F.col("o_orderkey") % 4 + 1).cast("int")).alias("surface"))
    return df.select("o_orderkey", "surface", F.array_join(temporal.values(temporal.parse_dates(F.col("surface"), anchor=F.col("d"))), ",").alias("found"))


@query
def q_dates_primary_fallback(spark, sf_dir):
    """What a primary parser resolved stands; what it left open, or missed, comes from the rules.  Sentences from the dates of orders."""
    o = tables.spread(tables.load_table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").cast("date").alias("d")))
    quarter, day = F.concat(F.date_format("d", "yyyy"), F.lit(" Q"), F.quarter("d").cast("string")), F.date_format("d", "MMMM d, yyyy")
    o = o.select("o_orderkey", "d", quarter.alias("q"), day.alias("day"), F.concat(F.lit("By "), quarter, F.lit(" sales doubled; by "), day, F.lit(" they fell.")).alias("text"))
    began = F.date_format(F.date_trunc("quarter", "d"), "yyyy-MM-dd")
    primary = F.array(F.struct(began.alias("value"), F.lit("date").alias("type"), F.col("q").alias("text")), F.struct(F.lit(None).cast("string").alias("value"), F.lit(None).cast("string").alias("type"), F.col("day").alias("text")))
    return o.select("o_orderkey", F.array_join(temporal.values(temporal.parse_dates(F.col("text"), primary)), ",").alias("both"), F.array_join(temporal.values(temporal.parse_dates(F.col("text"))), ",").alias("rules"))


@query
def q_temporal_fidelity(spark, sf_dir):
    return flat(validate(damaged_further(spark, sf_dir), judges=False), "temporal", "report_type", "row_id")


@query
def q_stray_year_example(spark, sf_dir):
    s = wl.wl_stray_year(spark, sf_dir)
    return s.select("report_type", "row_id", F.col("bag.tp").alias("tp"), F.col("bag.fp").alias("fp"), F.col("bag.fn").alias("fn"), exact("bag.p").alias("p"), exact("bag.f1").alias("f1"))


@query
def q_temporal_granular(spark, sf_dir):
    s = wl.wl_stray_year(spark, sf_dir)
    return s.select("report_type", "row_id", F.col("granular.tp").alias("tp"), F.col("granular.fp").alias("fp"), exact("granular.p").alias("p"))


# --- judges ---


@query
def q_claims_supported(spark, sf_dir):
    c = judging.claim_table(damaged_further(spark, sf_dir))
    return c.groupBy("report_type", "row_id").agg(F.count("*").alias("n_claims"), F.count_if("supported").alias("n_supported"), F.count_if("contradicted").alias("n_contradicted"), F.count_if("ungrounded").alias("n_ungrounded"))


@query
def q_judge_scores(spark, sf_dir):
    v = validate(damaged_further(spark, sf_dir))
    return v.select("report_type", "row_id", "judge.factuality", "judge.hallucination", "judge.coherence", exact("judge.overall").alias("overall"), "judge.consistent")


@query
def q_judge_by_type(spark, sf_dir):
    j = scoring.judge_table(scored_orders(spark, sf_dir, judges=True), ["report_type"])
    return j.select("report_type", *(exact(c).alias(c) for c in (*judging.DIMENSIONS, "overall")), "n")


@query
def q_judge_rubrics(spark, sf_dir):
    """The rubrics, and how many orders reach each level if the lines that were not returned are the good claims."""
    kept = tables.load_table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.avg((F.col("l_returnflag") == "N").cast("double")).alias("share"))
    reached = kept.groupBy(judging.rubric_level(F.col("share")).alias("level")).agg(F.count("*").alias("n"))
    r = judging.rubric_table(spark).join(F.broadcast(reached), "level", "left")
    return r.select("dimension", "level", exact("least_share").alias("least_share"), F.coalesce("n", F.lit(0)).alias("n_orders"))


@query
def q_judge_domain_rubrics(spark, sf_dir):
    """Damaged order reports by the rubric of a context: values as finance, handling by the general rubric."""
    r = damaged_further(spark, sf_dir).withColumn("domain", F.when(F.col("report_type") == "order_value", "finance").otherwise("operations"))
    return judging.judge_in_domain(r, judging.domain_rubric_table(spark)).select("report_type", "row_id", *judging.DIMENSIONS)


@query
def q_judge_vs_labels(spark, sf_dir):
    return wl.wl_judge_vs_labels(spark, sf_dir).select("n", *(exact(c).alias(c) for c in ("exact_share", "mean_gap", "kappa")))


@query
def q_claims_in_documents(spark, sf_dir):
    return wl.wl_claim_support(spark, sf_dir)


@query
def q_judge_table_domains(spark, sf_dir):
    return wl.wl_judge_table(spark, sf_dir).select("domain", *(exact(c).alias(c) for c in (*judging.DIMENSIONS, "overall")), "n")


# --- filter ---


@query
def q_weakest_metric(spark, sf_dir):
    return filtering.weakest_metric(scored_orders(spark, sf_dir)).select("dataset", "metric", exact("mean").alias("mean"))


@query
def q_filter_tau_090(spark, sf_dir):
    return filtering.filter_weakest(scored_orders(spark, sf_dir), "0.90").select("report_type", "row_id")


@query
def q_filter_precision_only(spark, sf_dir):
    return filtering.filter_reports(scored_orders(spark, sf_dir), "numeric", "0.90", on="precision").select("report_type", "row_id")


@query
def q_tau_sweep(spark, sf_dir):
    t = filtering.tau_sweep(scored_orders(spark, sf_dir), "numeric")
    return t.select("dataset", "tau", "n_reports", *(exact(c).alias(c) for c in ("retained_share", *(f"avg_{m}" for m in METRICS))))


@query
def q_tau_sweep_temporal(spark, sf_dir):
    t = filtering.tau_sweep(scored_orders(spark, sf_dir), "temporal", on="precision")
    return t.select("dataset", "tau", "n_reports", *(exact(c).alias(c) for c in ("retained_share", *(f"avg_{m}" for m in METRICS))))


@query
def q_tau_sweep_domains(spark, sf_dir):
    t = wl.wl_tau_sweep(spark, sf_dir)
    return t.select("domain", "tau", "n_reports", *(exact(c).alias(c) for c in ("retained_share", *(f"avg_{m}" for m in METRICS))))


@query
def q_averages_brands(spark, sf_dir):
    """Averages over many small tables, a brand each, of damaged reports: sizes differ, so weights matter."""
    a = wl.wl_brand_averages(spark, sf_dir)
    return a.select("kind", "averaging", *(exact(c).alias(c) for c in ("p", "r", "f1")), "n", "n_undefined")


@query
def q_reweighed_averages(spark, sf_dir):
    kept = filtering.filter_reports(scored_orders(spark, sf_dir), "numeric", "0.90")
    r = filtering.reweigh(kept, "report_type")
    return r.select("report_type", "n_reports", *(exact(c).alias(c) for c in r.columns[2:]))


# --- extraction ---


@query
def q_inferred_columns(spark, sf_dir):
    s = extraction.infer_schema(extraction.sample_reports(orders(spark, sf_dir)))
    return s.select("report_type", F.explode("columns").alias("column"))


@query
def q_extracted_values(spark, sf_dir):
    e = extraction.run_baseline(orders(spark, sf_dir))
    return e.select("report_type", "row_id", *(F.col("values")[c].alias(c) for c in ("order_key", "customer", "total_price", "order_date", "status", "priority", "segment")))


@query
def q_extracted_oracle_schema(spark, sf_dir):
    e = extraction.extract(orders(spark, sf_dir), wl.planned(spark, ("order_facts",)))
    return e.select("report_type", "row_id", *(F.col("values")[c].alias(c) for c in ("order_key", "customer", "total_price", "order_date", "status", "priority", "segment")))


@query
def q_extraction_malformed(spark, sf_dir):
    """Answers from the properties of events: whole, cut, a list, empty, no JSON or of another key, by the event's number."""
    e = tables.spread(tables.load_table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), F.get_json_object("props", "$.k").alias("k")))
    whole = F.concat(F.lit('{"a": "'), F.col("k"), F.lit('", "b": "y"}'))
    answers = F.array(whole, F.concat(F.lit('{"a": "'), F.col("k"), F.lit('"')), F.concat(F.lit('["'), F.col("k"), F.lit('"]')), F.lit(""), F.lit("not json"), F.concat(F.lit('{"b": "'), F.col("k"), F.lit('"}')))
    df = e.select("id", F.element_at(answers, (F.col("id") % 6 + 1).cast("int")).alias("raw_json"))
    return extraction.with_parsed(df).select("id", F.col("values")["a"].alias("a"), F.col("corrupt").isNotNull().alias("is_corrupt"))


def _names(spark, sf_dir):
    """True and inferred names of each brand and type of parts, a report type each: one differs in case and number, one is the same, two have other words, one has no partner."""
    name = lambda *parts: F.concat(*(F.lit(p) if isinstance(p, str) else p for p in parts))
    g = tables.load_table(spark, sf_dir, "part").groupBy("p_brand", "p_type").agg(F.min("p_name").alias("least"), F.max("p_name").alias("most"))
    keys = [F.lit("part").alias("dataset"), F.col("p_brand").alias("table_name"), F.col("p_type").alias("report_type")]
    brand, least, most = F.lower("p_brand"), F.col("least"), F.col("most")
    truth = F.array(name(brand, "_key"), F.col("p_type"), name(least, "_first"), name(most, "_last"))
    pred = F.array(name(F.upper("p_brand"), " Keys"), F.col("p_type"), name("last_", most), name("first_of_", least), F.lit("remark"))
    return g.select(*keys, truth.alias("columns")), g.select(*keys, pred.alias("columns"))


@query
def q_name_similarity_matrix(spark, sf_dir):
    m = matching.name_matrix(*_names(spark, sf_dir))
    return m.select("table_name", "report_type", "truth", "pred", exact("sim").alias("edit"), similarity.sim_exact(F.col("truth"), F.col("pred")).cast("int").alias("same"), similarity.sim_normalised(F.col("truth"), F.col("pred")).cast("int").alias("normalised"))


@query
def q_column_matching(spark, sf_dir):
    m = matching.match_columns(matching.name_matrix(*_names(spark, sf_dir)))
    return m.groupBy("table_name", "report_type").agg(F.count("*").alias("n_pairs"), exact(F.sum("sim")).alias("total"))


@query
def q_column_matching_exact_name(spark, sf_dir):
    return matching.match_columns(matching.name_matrix(*_names(spark, sf_dir)), "exact_name").select("table_name", "report_type", "truth", "pred")


@query
def q_column_matching_greedy(spark, sf_dir):
    """The trap, for each brand and type of parts: greedy takes .9 and is left with the least, the best is .8 twice."""
    g = tables.load_table(spark, sf_dir, "part").groupBy(F.col("p_brand").alias("table_name"), F.col("p_type").alias("report_type")).agg((F.sum("p_size") % 7).alias("more"))
    pair = lambda a, b, s: F.struct(F.concat("table_name", F.lit(a)).alias("truth"), F.concat("report_type", F.lit(b)).alias("pred"), s.cast("double").alias("sim"))
    trap = [pair(a, b, F.lit(s) if s > 0.1 else F.lit(s) + F.col("more") / 100.0) for a, b, s in oracles.TRAP]
    m = g.select(F.lit("part").alias("dataset"), "table_name", "report_type", F.inline(F.array(*trap)))
    g, e = (matching.match_columns(m, s).groupBy("table_name", "report_type").agg(F.sum("sim").alias("total")).select("table_name", "report_type", F.lit(s).alias("solver"), exact("total").alias("total")) for s in ("greedy", "exact"))
    return g.union(e)


@query
def q_column_scores(spark, sf_dir):
    truth, pred = _names(spark, sf_dir)
    s = scoring.score_columns(matching.match_columns(matching.name_matrix(truth, pred)), truth, pred)
    return s.select("table_name", "report_type", *(exact(c).alias(c) for c in ("p", "r", "f1")))


@query
def q_column_table(spark, sf_dir):
    return wl.wl_column_table(spark, sf_dir).select("dataset", "report_type", *(exact(c).alias(c) for c in ("p", "r", "f1")))


@query
def q_value_scores(spark, sf_dir):
    """Clean text, the true schema: whatever is written is found again."""
    pred = wl.planned(spark, ("order_facts",))
    mapping = matching.match_columns(matching.name_matrix(pred, pred))
    v = scoring.score_values(extraction.extract(orders(spark, sf_dir), pred), mapping)
    return v.select("report_type", "row_id", "n_truth", "n_pred", exact("p").alias("p"), exact("r").alias("r"), exact("f1").alias("f1"))


@query
def q_value_table(spark, sf_dir):
    return wl.wl_value_table(spark, sf_dir).select("dataset", "report_type", *(exact(c).alias(c) for c in ("p", "r", "f1", "f1_of_means")), "n")


@query
def q_value_table_exact(spark, sf_dir):
    return wl.wl_value_table(spark, sf_dir, weighting="exact").select("dataset", "report_type", *(exact(c).alias(c) for c in ("p", "r", "f1", "f1_of_means")), "n")


@query
def q_embedding_token_match(spark, sf_dir):
    return wl.wl_embedding_match(spark, sf_dir).select("label_a", "label_b", F.col("score").cast("decimal(10,4)").alias("score"))


# --- averages ---


@query
def q_macro_micro_size(spark, sf_dir):
    v = scored_orders(spark, sf_dir).withColumn("dataset", F.col("report_type")).withColumn("all", F.lit("orders"))
    return scoring.all_averages(v, "all").where("kind = 'numeric'").select("averaging", *(exact(c).alias(c) for c in ("p", "r", "f1")), "n", "n_undefined")


@query
def q_fidelity_rollup(spark, sf_dir):
    v = scored_orders(spark, sf_dir)
    return v.rollup("report_type", "damage").agg(F.count("*").alias("n"), exact(F.avg("numeric_f1")).alias("numeric_f1"), exact(F.avg("temporal_f1")).alias("temporal_f1"), F.grouping_id().cast("int").alias("level"))


@query
def q_score_cube(spark, sf_dir):
    v = scored_orders(spark, sf_dir)
    return v.cube("report_type", "damage").agg(F.sum("numeric_tp").alias("tp"), F.sum("numeric_fp").alias("fp"), F.sum("numeric_fn").alias("fn"))


@query
def q_numeric_table_domains(spark, sf_dir):
    return wl.wl_numeric_table(spark, sf_dir).select("domain", *(exact(c).alias(c) for c in ("p", "r", "f1", "f1_of_means")), "n", "n_undefined")


@query
def q_temporal_table_domains(spark, sf_dir):
    return wl.wl_temporal_table(spark, sf_dir).select("domain", *(exact(c).alias(c) for c in ("p", "r", "f1", "f1_of_means")), "n", "n_undefined")


@query
def q_averages_domains(spark, sf_dir):
    return wl.wl_weighted(spark, sf_dir).select("domain", "kind", "averaging", *(exact(c).alias(c) for c in ("p", "r", "f1")), "n", "n_undefined")


@query
def q_final_scores(spark, sf_dir):
    f = wl.wl_final_scores(spark, sf_dir)
    return f.select("dataset", *(exact(c).alias(c) for c in ("text_quality", "column_f1", "value_f1", "information_fidelity")))


@query
def q_model_grid(spark, sf_dir):
    g = wl.wl_model_grid(spark, sf_dir)
    return g.select("backend_id", *(exact(m).alias(m) for m in METRICS), "n")


@query
def q_asymmetry_gap(spark, sf_dir):
    gap = wl.wl_asymmetry(spark, sf_dir)
    return gap.select("dataset", *(exact(c).alias(c) for c in ("fidelity", "extraction", "incomplete_share", "gap")))


@query
def q_benchmark_summary(spark, sf_dir):
    s = wl.wl_corpus_summary(spark, sf_dir)
    return s.select("n_tables", "n_rows", exact("mean_columns").alias("mean_columns"), exact("mean_rows").alias("mean_rows"))


# --- workloads and operators around them ---


@query
def q_text_as_table(spark, sf_dir):
    return wl.wl_text_as_table(spark, sf_dir)


@query
def q_text_and_keyword(spark, sf_dir):
    """The same question by both ways: orders of a customer from extracted values, and passages that have the customer's name."""
    return wl.wl_text_and_keyword(spark, sf_dir)


@query
def q_keyword_vs_table(spark, sf_dir):
    return extraction.keyword_search(orders(spark, sf_dir), ["BUILDING", "1-URGENT"]).select("report_type", "row_id")


@query
def q_html_mentions(spark, sf_dir):
    return wl.wl_messy_mentions(spark, sf_dir, "pages")


@query
def q_conversation_mentions(spark, sf_dir):
    return wl.wl_messy_mentions(spark, sf_dir, "conversations")


@query
def q_orders_without_items(spark, sf_dir):
    o, li = tables.load_table(spark, sf_dir, "orders"), tables.load_table(spark, sf_dir, "lineitem")
    return o.join(li, o.o_orderkey == li.l_orderkey, "left_anti").select("o_orderkey")


@query
def q_tolerance_join(spark, sf_dir):
    o = tables.load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("a"), F.col("o_totalprice").alias("x"))
    p = tables.load_table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.max("l_extendedprice").alias("y")).select(F.col("l_orderkey").alias("b"), "y")
    return joins.tolerance_counts(o, p, "x", "y", "a", "b")


@query
def q_top_worst_reports(spark, sf_dir):
    v = scored_orders(spark, sf_dir)
    return v.orderBy("numeric_f1", F.col("row_id").cast("long"), "report_type").limit(20).select("report_type", "row_id", exact("numeric_f1").alias("numeric_f1"))


@query
def q_retention_window(spark, sf_dir):
    """How much each step of the threshold adds."""
    t = filtering.tau_sweep(scored_orders(spark, sf_dir), "numeric", include_unfiltered=False)
    own = W.partitionBy("dataset").orderBy(F.desc("tau"))
    return t.select("dataset", "tau", "n_reports", (F.col("n_reports") - F.lag("n_reports", 1, 0).over(own)).alias("added"), F.rank().over(own).alias("step"))


@query
def q_best_candidates(spark, sf_dir):
    m = matching.name_matrix(*_names(spark, sf_dir))
    return matching.best_candidates(m, 2).select("table_name", "report_type", "truth", "rank", "pred")


@query
def q_sketch_profile(spark, sf_dir):
    return planning.profile_sketches(tables.order_facts(spark, sf_dir), ["order_key", "total_price"]).select("column", (F.col("n_distinct") > 0).alias("any"))


@query
def q_lateral_candidates(spark, sf_dir):
    truth, pred = _names(spark, sf_dir)
    names = truth.select("dataset", "table_name", "report_type", F.explode("columns").alias("truth"))
    return matching.lateral_candidates(names, matching.name_matrix(truth, pred), 2).select(*(F.col(f"t.{c}").alias(c) for c in ("table_name", "report_type", "truth")), "pred", exact("sim").alias("sim"))


@query
def q_fact_history(spark, sf_dir):
    h = tables.fact_history(tables.facts_long(tables.load_table(spark, sf_dir, "events")), ["entity", "alias"])
    return h.select("entity", "alias", F.col("ts").cast("timestamp_ntz").alias("ts"), "quarter", *(exact(c).alias(c) for c in ("previous", "following", "first", "second", "place", "recent")))


@query
def q_order_statistics(spark, sf_dir):
    """Exact quartiles, values in order, and conditional counts by priority."""
    o = tables.load_table(spark, sf_dir, "orders").withColumn("o_totalprice", F.col("o_totalprice").cast("decimal(18,2)"))
    quartile = lambda q: exact(F.percentile("o_totalprice", q))
    return o.groupBy("o_orderpriority").agg(
        quartile(0.25).alias("q1"), quartile(0.5).alias("median"), quartile(0.75).alias("q3"), F.expr("listagg(distinct o_orderstatus, ',') within group (order by o_orderstatus)").alias("statuses"),
        F.expr("count(*) filter (where o_orderstatus = 'O')").alias("n_open"), F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"),
    )


@query
def q_profile_top(spark, sf_dir):
    return planning.profile_top(tables.order_facts(spark, sf_dir), ["segment", "status", "priority", "customer"], 3)


@query
def q_sample_by_segment(spark, sf_dir):
    """Stratified fractions: half of one segment, a tenth of another."""
    return planning.sample_fraction(tables.order_facts(spark, sf_dir), {"BUILDING": 0.5, "MACHINERY": 0.1}, "segment").select("row_id", "segment")


@query
def q_mention_bags(spark, sf_dir):
    """Dates of cells and passages as two bags of rows: what the array form counts per report, summed by report type."""
    side = lambda days, own: F.transform(days, lambda d: F.struct(F.lit(own).alias("in_truth"), d.alias("day")))
    both = F.concat(side(temporal.truth_dates(F.col("cells")), True), side(temporal.values(temporal.parse_dates(F.col("text"))), False))
    bags = joins.bag_difference(damaged_further(spark, sf_dir).select("report_type", "row_id", F.inline(both)), ["report_type", "row_id", "day"])
    return bags.groupBy("report_type").agg(F.sum("n_shared").alias("tp"), F.sum("n_extra").alias("fp"), F.sum("n_missing").alias("fn"))


@query
def q_scores_long(spark, sf_dir):
    """Means by report type with a row for each metric."""
    v = scored_orders(spark, sf_dir).groupBy("report_type").agg(*(exact(F.avg(m)).alias(m) for m in METRICS))
    return joins.to_long(v, ["report_type"], list(METRICS)).withColumnRenamed("name", "metric")


# --- streams ---


@query
def q_stream_reports(spark, sf_dir):
    """A file stream over all parts, run to its end, gives what the batch gives."""
    import uuid

    from .streaming import streams

    part = tables.load_table(spark, sf_dir, "part")
    source = streams.stream_table(spark, f"{sf_dir}/part.parquet*", part.schema)
    catalog = source.select(F.col("p_partkey").alias("part_key"), F.col("p_name").alias("part_name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").alias("size"), F.col("p_retailprice").cast("decimal(24,6)").alias("retail_price"), F.col("p_partkey").cast("string").alias("row_id"))
    scored = streams.stream_reports(catalog, DECLARED["part_catalog"]).select("report_type", "row_id", "numeric_tp", "numeric_fp", "numeric_fn")
    return streams.run_available(spark, scored, f"stream_{uuid.uuid4().hex}")


@query
def q_windowed_fidelity(spark, sf_dir):
    """Running fidelity of event reports by day of the event."""
    from .streaming import streams

    return streams.stream_fidelity(_event_scores(spark, sf_dir), "tumbling", "1 day").select("start", "n", "tp", "fp", "fn")


@query
def q_sliding_fidelity(spark, sf_dir):
    """Windows of a day that start every six hours."""
    from .streaming import streams

    return streams.stream_fidelity(_event_scores(spark, sf_dir), "sliding", "1 day", "6 hours").select("start", "n", "tp", "fp", "fn")


@query
def q_session_fidelity(spark, sf_dir):
    from .streaming import streams

    s = streams.stream_fidelity(_event_scores(spark, sf_dir), "session", "6 hours", by=("entity",))
    return s.groupBy("entity").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


def _event_scores(spark, sf_dir) -> DataFrame:
    e = tables.facts_long(tables.load_table(spark, sf_dir, "events")).withColumn("row_id", F.concat_ws("-", "entity", "alias", F.col("ts").cast("string")))
    plan = planning.Plan("facts", (planning.declared("facts", "fact", "entity", "value"),))
    text = generation.passage(F.col("row_id"), plan.types[0], {f.name: f for f in e.schema.fields})
    cells = F.array(*(generation.cell(f) for f in e.schema.fields if f.name in ("entity", "value")))
    r = e.select("entity", "ts", "row_id", cells.alias("cells"), text.alias("text"))
    return validate(r, judges=False)


def queries() -> dict[str, Query]:
    return dict(_all)


def oracle_sql() -> dict[str, str]:
    from . import experiment_sql

    return oracles.build() | experiment_sql.build()
