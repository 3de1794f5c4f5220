"""What is asked of a model in each role, and how its answers are read.

Each function takes rows and a ``CachedCalls`` and gives the rows that the rules would have given, so
everything after it is the same.  A row whose call failed, or whose answer is not of the form asked for,
has nulls and its error in ``error``.

| role | request | answer |
|-|-|-|
| plan | table, columns, rows, max_types | [{"report_type", "columns"}] |
| generate | cells (name, value) | {"text"} |
| judge | dimension, grounding, text, cells (for grounding by the source) | {"score", "reason", "claims": [{"text", "supported"}]} |
| dates | text, anchor | [{"value", "type", "text"}] |
| schema | texts | {"columns": [...]} |
| extract | text, columns | {column: value} |
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import temporal
from .backends import CachedCalls

KEYS = ["dataset", "table_name", "report_type"]
VERDICT = "struct<score:int,reason:string,claims:array<struct<text:string,supported:boolean>>>"


def shown(cells: Column) -> Column:
    """What a model sees of a row: names and surfaces of the planned cells that are not null."""
    return F.transform(F.filter(cells, lambda c: c["surface"].isNotNull()), lambda c: F.struct(c["name"].alias("name"), c["surface"].alias("value")))


def write_texts(cells: DataFrame, calls: CachedCalls) -> DataFrame:
    """Rows with ``cells`` get ``text`` and ``error``."""
    asked = calls.answers(cells, "generate", F.to_json(F.struct(shown(F.col("cells")).alias("cells"))))
    return asked.withColumn("text", F.from_json("response", "text string")["text"]).drop("response", "cached")


def judge_texts(reports: DataFrame, calls: CachedCalls, dimensions: tuple[str, ...] = ("factuality", "hallucination", "coherence"), grounding: str = "source") -> DataFrame:
    """Reports with ``judge``: a level of 1 to 5 a dimension, overall, the supported share of claims and whether levels fit it.

    ``grounding``: ``source`` shows the row beside the text, ``world`` the text alone, to be judged by
    general knowledge.  All dimensions are asked for in one pass.
    """
    from ..operators.judging import self_consistency

    columns = list(reports.columns)
    cells = F.when(F.lit(grounding == "source"), shown(F.col("cells")))
    long = reports.select(*columns, F.explode(F.array(*map(F.lit, dimensions))).alias("__dimension"))
    request = F.to_json(F.struct(F.col("__dimension").alias("dimension"), F.lit(grounding).alias("grounding"), "text", cells.alias("cells")))
    verdict = F.from_json("response", VERDICT)
    asked = calls.answers(long, "judge", request).withColumn("__v", verdict)
    score = F.when(F.col("__v.score").between(1, 5), F.col("__v.score"))
    keys = [c for c in columns if c not in ("text", "cells")]
    own = lambda d, c: F.max(F.when(F.col("__dimension") == d, c))
    claims = F.flatten(F.collect_list(F.col("__v.claims")))
    wide = asked.groupBy(*keys).agg(*(own(d, score).alias(f"__{d}") for d in dimensions), claims.alias("__claims"), F.max("error").alias("error"))
    supported = F.try_divide(F.size(F.filter("__claims", lambda c: c["supported"])).cast("double"), F.size("__claims").cast("double"))
    overall = sum((F.col(f"__{d}") for d in dimensions[1:]), F.col(f"__{dimensions[0]}")) / float(len(dimensions))
    lowest = F.least(*(F.col(f"__{d}") for d in dimensions)) if len(dimensions) > 1 else F.col(f"__{dimensions[0]}")
    made = F.struct(*(F.col(f"__{d}").alias(d) for d in dimensions), overall.alias("overall"), supported.alias("supported_share"), self_consistency(lowest, supported).alias("consistent"))
    return wide.select(*keys, made.alias("judge"), "error")


def primary_dates(texts: DataFrame, calls: CachedCalls, text: str = "text", anchor: str | None = None) -> DataFrame:
    """Rows with ``primary``: the mentions that a context-aware parser resolved, for ``temporal.parse_dates``; null where it failed."""
    request = F.to_json(F.struct(F.col(text).alias("text"), (F.col(anchor).cast("string") if anchor else F.lit(None).cast("string")).alias("anchor")))
    asked = calls.answers(texts, "dates", request)
    return asked.withColumn("primary", F.from_json("response", temporal.MENTIONS)).drop("response", "cached", "error")


def infer_columns(sample: DataFrame, calls: CachedCalls, keys: list[str] | None = None) -> DataFrame:
    """keys, columns: one request a report type, with its sampled texts in the order of their rows."""
    keys = keys or KEYS
    texts = F.transform(F.array_sort(F.collect_list(F.struct(F.md5("row_id").alias("k"), "row_id", "text"))), lambda x: x["text"])
    groups = sample.groupBy(*keys).agg(texts.alias("texts"))
    asked = calls.answers(groups, "schema", F.to_json(F.struct("texts")))
    named = F.array_distinct(F.filter(F.from_json("response", "columns array<string>")["columns"], lambda c: c.isNotNull() & (c != "")))
    return asked.select(*keys, named.alias("columns")).where("columns is not null")


def extract_values(reports: DataFrame, calls: CachedCalls) -> DataFrame:
    """Reports that hold their type's ``columns`` get ``raw_json``, ``values`` over these columns, and ``error``."""
    asked = calls.answers(reports, "extract", F.to_json(F.struct("text", "columns")))
    parsed = F.from_json("response", "map<string,string>", {"mode": "PERMISSIVE"})
    values = F.map_filter(F.coalesce(parsed, F.expr("cast(map() as map<string,string>)")), lambda k, v: F.array_contains(F.col("columns"), k) & v.isNotNull())
    return asked.withColumn("values", values).withColumnRenamed("response", "raw_json").drop("cached")
