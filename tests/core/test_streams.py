import datetime as dt
import os

from pyspark.sql import functions as F

from tabletext.functions import sqlfuncs
from tabletext.operators.validation import validate
from tabletext.operators.generation import generate
from tabletext.plans.planning import DECLARED
from tabletext.sources import tables
from tabletext.streaming import streams


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_stream_equals_batch(spark, sf, tmp_path):
    batch = tables.part_catalog(spark, sf)
    batch.repartition(3).write.parquet(f"{tmp_path}/in")
    source = streams.stream_table(spark, f"{tmp_path}/in", batch.schema)
    keep = ["report_type", "row_id", "numeric_tp", "numeric_fp"]
    out = streams.run_available(spark, streams.stream_reports(source, DECLARED["part_catalog"]).select(*keep), "s1")
    assert rows(out) == rows(validate(generate(batch, DECLARED["part_catalog"])).select(*keep))


def test_latest_dedupe_late_and_sink(spark, tmp_path):
    t = lambda h: dt.datetime(2024, 1, 1, h)
    df = spark.createDataFrame([("a", 1.0, t(1)), ("a", 2.0, t(3)), ("b", 5.0, t(2)), ("a", 2.0, t(3))], "k string, value double, ts timestamp")
    df.coalesce(1).write.parquet(f"{tmp_path}/in")
    source = lambda: streams.stream_table(spark, f"{tmp_path}/in", df.schema)
    assert rows(streams.run_available(spark, streams.stream_latest(source(), ["k"]), "s2", "complete").select("k", "value")) == [("a", 2.0), ("b", 5.0)]
    assert streams.run_available(spark, streams.stream_dedupe(source(), ["k", "value"], "1 hour"), "s3").count() == 3
    for _ in range(2):
        streams.stream_sink(streams.with_lateness(source(), "1 hour"), f"{tmp_path}/out", f"{tmp_path}/cp").awaitTermination()
    assert spark.read.parquet(f"{tmp_path}/out").count() == 4
    verdicts = spark.createDataFrame([("a", 5, t(2)), ("b", 4, t(9))], "k string, score int, ts timestamp")
    verdicts.coalesce(1).write.parquet(f"{tmp_path}/v")
    joined = streams.stream_join_verdicts(source(), streams.stream_table(spark, f"{tmp_path}/v", verdicts.schema), "2 hours", "1 hour", key="k")
    assert rows(streams.run_available(spark, joined.select("k", "value", "score"), "s4")) == [("a", 1.0, 5)]


def test_sql_functions(spark):
    sqlfuncs.register_functions(spark)
    r = spark.sql("select tt_f1(0.8, 1.0) f, tt_prf(4, 5, 4).p p, tt_within(1000, 1001) w, tt_sim_edit('abcd', 'abce') s, tt_text_quality(5, 4, 3) q, tt_rubric_level(0.75) l").first()
    assert (round(r.f, 4), r.p, r.w, r.s, r.q, r.l) == (0.8889, 0.8, True, 0.75, 4.0, 3)
    assert spark.sql("select * from tt_mentions('due May 3, 2021 or 2022 Q4')").count() == 2
    assert spark.sql("select claim from tt_claims('One. Two is 3.5. End.') order by pos").count() == 3


def test_facts(spark, sf):
    facts = tables.facts_long(tables.load_table(spark, sf, "events"))
    wide = tables.company_facts_wide(spark, sf)
    assert wide.count() == facts.select("entity").distinct().count() and len(wide.columns) == 18
    late = tables.asof_facts(facts, facts.select("entity").distinct().withColumn("at", F.lit("1999-01-01").cast("timestamp_ntz")), ["entity"])
    assert late.where("value is not null").count() == 0


def test_late_rows_are_counted(spark, tmp_path):
    t = lambda h: dt.datetime(2024, 1, 1, h)
    for i, hour in enumerate((10, 20, 1, 21)):
        spark.createDataFrame([("a", float(i), t(hour))], "k string, value double, ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    schema = spark.read.parquet(f"{tmp_path}/in/0").schema
    for i in range(4):  # files are read in the order of their times
        for f in (tmp_path / "in" / str(i)).glob("*.parquet"):
            os.utime(f, (1_700_000_000 + i, 1_700_000_000 + i))
    source = streams.with_lateness(streams.stream_table(spark, f"{tmp_path}/in/*", schema), "1 hour")
    counts = source.groupBy(streams.windowed("sliding", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select("w.start", "n")
    query = counts.writeStream.format("parquet").option("checkpointLocation", f"{tmp_path}/cp").outputMode("append").trigger(availableNow=True).start(f"{tmp_path}/out")
    query.awaitTermination()
    assert streams.late_rows(query) == 2  # the row of 1 o'clock, in its two windows
    assert spark.read.parquet(f"{tmp_path}/out").where(F.hour("start") < 5).count() == 0


def test_a_stream_without_rows(spark, tmp_path):
    empty = spark.createDataFrame([], "k string, value double, ts timestamp")
    empty.coalesce(1).write.parquet(f"{tmp_path}/in")
    assert streams.run_available(spark, streams.stream_table(spark, f"{tmp_path}/in", empty.schema), "s5").collect() == []
