"""Joins that the methods need and Spark has no operator for."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.fidelity import TOLERANCE, within
from ..shipping import ship
from ..sources.tables import spread

#: Bytes of the item side of a containment join that may be broadcast.
MAX_ITEM_BYTES = 8 << 20


def tolerance_join(a: DataFrame, b: DataFrame, left: str, right: str, rel: str = TOLERANCE) -> DataFrame:
    """Pairs of numbers within a relative tolerance of the left one.

    Positive numbers fall into logarithmic buckets as wide as the tolerance; a partner is in the same or
    a neighbouring bucket, so the join is on equality.  Zeros and negative numbers have buckets of
    their own.
    """
    step = float(rel)

    def bucket(c):
        x = F.col(c).cast("double")
        size = F.floor(F.ln(F.abs(x)) / F.lit(step)).cast("long")
        return F.when(x == 0, F.struct(F.lit(0).alias("sign"), F.lit(0).cast("long").alias("at"))).otherwise(F.struct(F.signum(x).cast("int").alias("sign"), size.alias("at")))

    near = b.withColumn("__b", bucket(right))
    spread = a.withColumn("__a", bucket(left)).withColumn("__at", F.explode(F.when(F.col("__a.sign") == 0, F.array(F.col("__a.at"))).otherwise(F.sequence(F.col("__a.at") - 2, F.col("__a.at") + 2))))
    joined = spread.join(near, (F.col("__a.sign") == F.col("__b.sign")) & (F.col("__at") == F.col("__b.at")))
    return joined.where(within(F.col(left).cast("decimal(24,6)"), F.col(right).cast("decimal(24,6)"), rel)).drop("__a", "__b", "__at")


def tolerance_counts(a: DataFrame, b: DataFrame, left: str, right: str, left_id: str, right_id: str, rel: str = TOLERANCE) -> DataFrame:
    """left_id, n, least: how many numbers are within the tolerance of the left one, and the least id of them.

    No pair is formed.  What is within the tolerance of a number is a range; ranges are cut at the
    borders of logarithmic buckets, and in each bucket two binary searches give the count and a table
    of minima over powers of two the least id.  Numbers are whole millionths; ids are whole numbers.
    """
    ship(a.sparkSession)
    step = float(rel)
    exact = lambda c: (F.col(c).cast("decimal(24,6)") * F.lit(1_000_000)).cast("long")

    def bucket(c):
        return (F.signum(c) * F.floor(F.log1p(F.abs(c)) / F.lit(step))).cast("long")

    share = F.floor(F.abs(F.col("__x")).cast("decimal(38,6)") * F.lit(rel).cast("decimal(4,3)")).cast("long")
    ranges = a.select(F.col(left_id).cast("long").alias("__id"), exact(left).alias("__x")).where("__x is not null")
    ranges = ranges.select("__id", (F.col("__x") - share).alias("__low"), (F.col("__x") + share).alias("__high"))
    ranges = ranges.withColumn("__at", F.explode(F.sequence(bucket(F.col("__low")), bucket(F.col("__high")))))
    points = b.select(F.col(right_id).cast("long").alias("__id"), exact(right).alias("__y")).where("__y is not null")
    points = points.withColumn("__at", bucket(F.col("__y")))
    found = ranges.groupBy("__at").cogroup(points.groupBy("__at")).applyInArrow(_counted, "id long, n long, least long")
    return found.groupBy(F.col("id").alias(left_id)).agg(F.sum("n").alias("n"), F.min("least").alias("least"))


def _counted(ranges: pa.Table, points: pa.Table) -> pa.Table:
    """Of the ranges that meet a point: id, number of points, least id of them."""
    if not ranges.num_rows or not points.num_rows:
        return pa.table({c: pa.array([], pa.int64()) for c in ("id", "n", "least")})
    points = points.sort_by("__y")
    y, minima = points["__y"].to_numpy(), [points["__id"].to_numpy()]
    while len(y) >= 2 << len(minima) - 1:
        half = 1 << len(minima) - 1
        minima.append(np.minimum(minima[-1][:-half], minima[-1][half:]))
    low, high = np.searchsorted(y, ranges["__low"].to_numpy(), "left"), np.searchsorted(y, ranges["__high"].to_numpy(), "right")
    some = high > low
    low, high, ids = low[some], high[some], ranges["__id"].to_numpy()[some]
    level = np.frexp(high - low)[1] - 1
    least = np.zeros(len(ids), np.int64)
    for k in np.unique(level).tolist():
        own = level == k
        least[own] = np.minimum(minima[k][low[own]], minima[k][high[own] - (1 << k)])
    return pa.table({"id": ids, "n": (high - low).astype(np.int64), "least": least})


def contains_join(docs: DataFrame, items: DataFrame, max_bytes: int = MAX_ITEM_BYTES) -> DataFrame:
    """Documents that contain an item's text.  The items are small; their size is checked before they are sent to all tasks.

    Beyond the bound they are sent in parts of about that size, one pass over the documents each, with the same test.
    """
    docs = spread(docs)
    size, count = items.agg(F.coalesce(F.sum(F.octet_length("item_text")), F.lit(0)), F.count("*")).first()
    n = max(1, min(-(-size // max_bytes), count))
    part = F.pmod(F.xxhash64(*items.columns), F.lit(n))
    parts = [items if n == 1 else items.where(part == i) for i in range(n)]
    return reduce(DataFrame.union, [docs.join(F.broadcast(p), F.col("text").contains(F.col("item_text"))) for p in parts])


def bag_difference(sides: DataFrame, keys: list[str], side: str = "in_truth") -> DataFrame:
    """keys, n_shared, n_missing, n_extra of rows marked as of the truth or not: repeats count.

    What ``intersectAll`` and two ``exceptAll`` give, from one aggregation instead of three.
    """
    counts = sides.groupBy(*keys).agg(F.count_if(F.col(side)).alias("__t"), F.count_if(~F.col(side)).alias("__f"))
    more = lambda a, b: F.greatest(F.col(a) - F.col(b), F.lit(0)).cast("long")
    return counts.select(*keys, F.least("__t", "__f").alias("n_shared"), more("__t", "__f").alias("n_missing"), more("__f", "__t").alias("n_extra"))


def to_long(wide: DataFrame, keys: list[str], columns: list[str]) -> DataFrame:
    return wide.unpivot(keys, columns, "name", "value")
