"""The same methods over streams of rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.generation import RenderStyle, generate
from ..operators.validation import validate
from ..plans.planning import Plan
from ..storage import folder


def stream_table(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def with_lateness(sdf: DataFrame, delay: str, ts: str = "ts") -> DataFrame:
    return sdf.withWatermark(ts, delay)


def stream_reports(sdf: DataFrame, plan: Plan, style: RenderStyle = RenderStyle()) -> DataFrame:
    """Reports with their scores, row by row: no state."""
    return validate(generate(sdf, plan, style))


def stream_latest(sdf: DataFrame, keys: list[str], value: str = "value", ts: str = "ts") -> DataFrame:
    """The newest value of each key so far (update or complete mode)."""
    return sdf.groupBy(*keys).agg(F.max_by(value, ts).alias(value), F.max(ts).alias(ts))


def windowed(kind: str, size: str, slide: str | None = None, ts: str = "ts") -> Column:
    if kind == "tumbling":
        return F.window(ts, size)
    if kind == "sliding":
        return F.window(ts, size, slide)
    return F.session_window(ts, size)


def stream_fidelity(sdf: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str | None = None, ts: str = "ts", by: tuple[str, ...] = ()) -> DataFrame:
    """Sums of scores by window of event time; batch frames work as well."""
    return sdf.groupBy(windowed(kind, size, slide, ts).alias("w"), *by).agg(
        F.count("*").alias("n"), F.sum("numeric_tp").alias("tp"), F.sum("numeric_fp").alias("fp"), F.sum("numeric_fn").alias("fn"), F.avg("numeric_p").alias("p"), F.avg("numeric_r").alias("r")
    ).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n", "tp", "fp", "fn", "p", "r")


def stream_dedupe(sdf: DataFrame, keys: list[str], delay: str, ts: str = "ts") -> DataFrame:
    return sdf.withWatermark(ts, delay).dropDuplicatesWithinWatermark(keys)


def stream_join_verdicts(reports: DataFrame, verdicts: DataFrame, within: str, delay: str, key: str = "row_id") -> DataFrame:
    """Verdicts that come at most so long after their report."""
    r = reports.withWatermark("ts", delay).alias("r")
    v = verdicts.withColumnRenamed("ts", "verdict_ts").withColumnRenamed(key, "__key").withWatermark("verdict_ts", delay).alias("v")
    return r.join(v, F.expr(f"r.{key} = v.__key and v.verdict_ts >= r.ts and v.verdict_ts <= r.ts + interval {within}")).drop("__key")


def stream_sink(sdf: DataFrame, path: str, checkpoint: str, once: bool = True):
    """Each batch to a folder of its own id, replaced if the batch is replayed."""

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    writer = sdf.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if once else writer).start()


def late_rows(query) -> int:
    """Rows that a finished or running stream left out because they came after the watermark."""
    return sum(int(o["numRowsDroppedByWatermark"]) for p in query.recentProgress for o in p["stateOperators"])


def run_available(spark: SparkSession, sdf: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what there is, into a table in the shared folder; in complete mode the last result replaces the others."""
    rows, checkpoint = folder(spark, name), folder(spark, f"{name}-checkpoint")

    def put(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{rows}/batch={0 if mode == 'complete' else batch_id}")

    query = sdf.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(sdf.schema).parquet(rows).select(*sdf.columns)
