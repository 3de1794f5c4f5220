"""Histogram sort: splitters found by counting, rows exchanged once.

The order is by a digest of the text, then by a digest of document id and row number, so rows with equal
texts are neighbours and rows that are equal altogether still have an order.
Each round counts the exact bytes below some candidate keys in every task, sums the counts and
narrows the bracket of each splitter, until every splitter is within the tolerance of its target or
its bracket has no key left between its ends.  While candidates are digests alone, a splitter falls
between groups of equal texts; only where one group is heavier than the tolerance does its bracket
close on a single digest, and the second digests inside that group become the candidates.  Then rows go to their
place in one exchange.

A shard is split further into parts of bounded size, by splitters of the same kind, so that no task
sorts a whole shard; slots count on from part to part.

Odd input: a null text sorts as the empty text, has no bytes and counts 1; a null id is an id like any
other; repeated rows are placed each, also in different shards; an empty table gives an empty result.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .storage import partitions_for, written

#: Rows of the narrow key table that a task sorts, about.
PART_ROWS = 1 << 20
#: Candidate keys that one round counts, for all splitters together, and for one at least.
PROBES, LEAST_PROBES = 4096, 16

Key = tuple[int, int]  # both digests, as unsigned 64-bit numbers
LAST = (1 << 64) - 1


def keyed(docs: DataFrame, id: str = "doc_id", text: str = "text") -> DataFrame:
    """The narrow table that all rounds read: id, key, size and checksum, without the text."""
    whole = F.coalesce(F.col(text), F.lit(""))
    return docs.select(
        F.col(id).cast("long").alias("doc_id"),
        F.xxhash64(whole).alias("digest"),
        (F.octet_length(whole) + F.lit(1)).cast("long").alias("size"),
        F.crc32(whole.cast("binary")).alias("text_crc32"),
        F.xxhash64(F.col(id).cast("long"), F.monotonically_increasing_id()).alias("tie"),
    )


def _ordered(column: pa.Array) -> np.ndarray:
    """Signed longs as unsigned numbers of the same order; null first."""
    if column.null_count:
        column = column.fill_null(-(1 << 63))
    return column.to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64) ^ np.uint64(1 << 63)


def below(digests: np.ndarray, ties: np.ndarray, probes: list[Key]) -> np.ndarray:
    """For each row, the number of probes that are at or below its key."""
    p = np.array([x[0] for x in probes], dtype=np.uint64)
    q = np.array([x[1] for x in probes], dtype=np.uint64)
    low, high = np.searchsorted(p, digests, "left"), np.searchsorted(p, digests, "right")
    place = high.copy()
    same = np.flatnonzero(high > low)  # rows whose digest is that of a probe: the second one decides
    for a in np.unique(low[same]):
        own = same[low[same] == a]
        place[own] = a + np.searchsorted(q[a : high[own[0]]], ties[own], "right")
    return place


def _histogram(probes: list[Key]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes, rows = np.zeros(len(probes) + 1, np.int64), np.zeros(len(probes) + 1, np.int64)
        for batch in batches:
            at = below(_ordered(batch.column("digest")), _ordered(batch.column("tie")), probes)
            np.add.at(sizes, at, batch.column("size").to_numpy())
            rows += np.bincount(at, minlength=len(rows))
        full = np.flatnonzero(rows)
        yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array(sizes[full]), pa.array(rows[full])], names=["place", "bytes", "rows"])

    return run


def count_below(keys: DataFrame, probes: list[Key]) -> tuple[np.ndarray, np.ndarray]:
    """Exact bytes and rows below each probe, and in all.  At most a row a probe comes to the driver."""
    counted = keys.select("tie", "digest", "size").mapInArrow(_histogram(probes), "place int, bytes long, rows long").groupBy("place").agg(F.sum("bytes").alias("bytes"), F.sum("rows").alias("rows"))
    sizes = np.zeros((2, len(probes) + 1), np.int64)
    for r in counted.collect():
        sizes[:, r["place"]] = r["bytes"], r["rows"]
    sizes = np.cumsum(sizes, axis=1)
    return sizes[0], sizes[1]


def _between(low: Key, high: Key, n: int) -> list[Key]:
    """Up to n keys strictly between two keys: first digests as long as the bracket spans some, then second ones."""
    if high[0] - low[0] > 1:
        span = high[0] - low[0]
        return sorted({(low[0] + span * i // (n + 1), 0) for i in range(1, n + 1)} - {low, high} - {(low[0], 0)})
    a, b = (low[1], high[1]) if low[0] == high[0] else (low[1], LAST + 1)
    return sorted({(low[0], a + (b - a) * i // (n + 1)) for i in range(1, n + 1)} - {low, high})


class Border:
    """The bracket of one splitter: the nearest keys known at or below its target, and above it."""

    def __init__(self, target: float, total: int, rows: int):
        self.target, self.low, self.high = target, (0, 0), (LAST, LAST)
        self.bytes, self.rows, self.done = [0, total], [0, rows], False

    def narrow(self, probes: list[Key], sizes: list[int], rows: list[int]) -> None:
        at = bisect_right(sizes, self.target)
        if at and probes[at - 1] > self.low:
            self.low, self.bytes[0], self.rows[0] = probes[at - 1], sizes[at - 1], rows[at - 1]
        if at < len(probes) and probes[at] < self.high:
            self.high, self.bytes[1], self.rows[1] = probes[at], sizes[at], rows[at]

    def best(self) -> tuple[Key, int]:
        return min((self.low, self.bytes[0]), (self.high, self.bytes[1]), key=lambda x: abs(x[1] - self.target))


def splitters(keys: DataFrame, shards: int, tolerance: float = 0.005) -> tuple[list[Key], list[int], int]:
    """For each border between shards a key and the exact bytes below it; and the bytes in all.

    A border is done when it is within the tolerance (a share of a mean shard), when its bracket holds
    one row at most, or when no key is left inside the bracket.
    """
    rows, total = keys.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    borders = [Border(total * i / shards, total, rows) for i in range(1, shards)]
    while open_ := [b for b in borders if not b.done]:
        each = max(LEAST_PROBES, PROBES // len(open_))
        probes = sorted({p for b in open_ for p in _between(b.low, b.high, each)})
        sizes, counts = count_below(keys, probes) if probes else ([0], [0])
        sizes, counts = list(map(int, sizes[:-1])), list(map(int, counts[:-1]))
        for b in open_:
            b.narrow(probes, sizes, counts)
            b.done = abs(b.best()[1] - b.target) <= tolerance * total / shards or b.rows[1] - b.rows[0] <= 1 or not _between(b.low, b.high, 1)
    return [b.best()[0] for b in borders], [b.best()[1] for b in borders], total


def _place(borders: list[Key]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = below(_ordered(batch.column("digest")), _ordered(batch.column("tie")), borders)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(at, pa.int32())], names=[*batch.schema.names, "part"])

    return run


def histogram_sort(docs: DataFrame, shards: int = 8, tolerance: float = 0.005, id: str = "doc_id", text: str = "text", part_rows: int = PART_ROWS) -> DataFrame:
    """doc_id, size, text_crc32, shard and slot of each document; shards of near equal bytes."""
    keys = written(keyed(docs, id, text), "shard-keys")
    rows = keys.count()
    parts = max(1, -(-rows // (shards * part_rows)), -(-min(rows // 1000, partitions_for(docs.sparkSession, 0, 1)) // shards))
    borders, _, _ = splitters(keys, shards * parts, tolerance)
    placed = keys.mapInArrow(_place(borders), "doc_id long, digest long, size long, text_crc32 long, tie long, part int")
    placed = placed.repartition(partitions_for(docs.sparkSession, shards * parts, 1), "part")
    return slots(placed, parts)


def slots(placed: DataFrame, parts: int) -> DataFrame:
    """Slots that count on from part to part.  The counts of parts are as few as there are parts."""
    inside = F.row_number().over(W.partitionBy("part").orderBy("digest", "tie", "doc_id", "text_crc32")) - 1
    numbered = written(placed.withColumn("inside", inside), "shard-parts")
    shard = F.floor(F.col("part") / F.lit(parts)).cast("int")
    counts = numbered.groupBy("part").agg(F.count("*").alias("rows")).select("part", shard.alias("shard"), "rows")
    before = counts.select("part", "shard", (F.sum("rows").over(W.partitionBy("shard").orderBy("part")) - F.col("rows")).alias("before"))
    return numbered.join(F.broadcast(before), "part").select("doc_id", "size", "text_crc32", "shard", (F.col("before") + F.col("inside")).cast("long").alias("slot"))


def op1(docs: DataFrame) -> DataFrame:
    sharded = histogram_sort(docs)
    return sharded.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
