"""Where reports, scores and manifests go."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_reports(df: DataFrame, path: str, by: tuple[str, ...] = ("dataset", "table_name", "report_type")) -> None:
    """Parquet by report type; a rewrite replaces only the partitions that it has rows for."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*by).parquet(path)


def release_jsonl(reports: DataFrame, path: str) -> None:
    """A line a report: its key, its text, and the true cells as a dictionary."""
    truth = F.map_from_entries(F.transform(F.filter("cells", lambda c: c["surface"].isNotNull()), lambda c: F.struct(c["name"], c["surface"])))
    reports.select("dataset", "table_name", "report_type", "row_id", "text", truth.alias("truth")).write.mode("overwrite").json(path)


def manifest(spark: SparkSession, path: str, run_id: str, **facts: str) -> None:
    rows = [(run_id, k, str(v)) for k, v in facts.items()]
    spark.createDataFrame(rows, "run_id string, key string, value string").coalesce(1).write.mode("append").parquet(path)


def cost_report(calls: DataFrame) -> DataFrame:
    """role, calls, cached, characters in and out, from a log of calls."""
    return calls.groupBy("role").agg(F.count("*").alias("calls"), F.count_if("cached").alias("cached"), F.sum(F.length("request")).alias("chars_in"), F.sum(F.length("response")).alias("chars_out"))
