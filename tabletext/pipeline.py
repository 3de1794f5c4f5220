"""Any table to a scored benchmark: plan, reports, validation, filter, extraction, scores."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .operators import extraction, filtering, generation, matching, scoring
from .operators.validation import validate, validate_with
from .plans.planning import Plan
from .sources import sinks, tables
from .workloads import plan_for


@dataclass
class Benchmark:
    plan: Plan
    reports: DataFrame
    validation: DataFrame
    retained: DataFrame
    columns: DataFrame
    values: DataFrame


def benchmark_table(spark: SparkSession, df: DataFrame, name: str, plan: Plan | None = None, tau: str = "0.90", style: generation.RenderStyle = generation.RenderStyle(), path: str | None = None, backend=None, grounding: str = "source") -> Benchmark:
    """With a path, reports and validation are written between the stages and read again.

    With a backend (``CachedCalls``) a model plans, writes, judges, reads dates, names columns and extracts.
    """
    if "row_id" not in df.columns:
        df = tables.with_row_id(df)
    plan = plan or plan_for(df, name, backend.backend if backend else None)
    reports = generation.generate(df, plan, style, backend=backend)
    if path:
        sinks.write_reports(reports, f"{path}/reports")
        reports = spark.read.schema(reports.schema).parquet(f"{path}/reports").select(*reports.columns)
    v = validate(reports) if backend is None else validate_with(reports, backend, grounding)
    if path:
        v.write.mode("overwrite").parquet(f"{path}/validation")
        v = spark.read.schema(v.schema).parquet(f"{path}/validation")
    retained = filtering.filter_weakest(v, tau)
    kept = reports.join(retained.select(*scoring.KEYS, "row_id"), [*scoring.KEYS, "row_id"], "left_semi")
    schema = extraction.infer_schema(extraction.sample_reports(kept), backend=backend)
    truth = extraction.oracle_schema(kept) if "table_name" in df.columns else extraction.planned_schema(spark, plan)
    mapping = matching.match_columns(matching.name_matrix(truth, schema))
    return Benchmark(plan, reports, v, retained, scoring.score_columns(mapping, truth, schema), scoring.score_values(extraction.extract(kept, schema, backend), mapping))
