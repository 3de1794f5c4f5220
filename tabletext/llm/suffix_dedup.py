"""Suffix-array deduplication: maximal repeats from the common-prefix interval tree of a shard.

A shard's suffixes are those that start at its anchors.  They are sorted, neighbours' common prefixes
are measured, and a scan with a stack yields the tree of common-prefix intervals.  In each interval
the contexts to the left are compared as well: where they differ at once, the repeat cannot be
extended to the left for all; where groups of them agree, these occurrences share more than the
prefix.  Each occurrence is reported with the longest left extension that any other occurrence of
its interval shares, so every occurrence of every repeat is found, not just neighbours in the array.

Odd input: null texts count as empty; texts shorter than a window have no window; repeated rows repeat
each other; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .anchors import SHARD_ROWS, Units, anchor_table, apply_spans, keys_of, plainly_named, regions, repeat_spans, repeated
from .storage import partitions_for, written

LENGTH = 200
#: Interval members whose left contexts are compared at once.
CHUNK = 200_000


def _matrix(parts: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(p.ljust(width, b"\0") for p in parts), np.uint8).reshape(len(parts), width), np.array([len(p) for p in parts])


def common(matrix: np.ndarray, lengths: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Length of the common prefix of rows a and b."""
    width = matrix.shape[1]
    differs = np.empty((len(a), width + 1), bool)
    np.not_equal(matrix[a], matrix[b], out=differs[:, :width])
    differs[:, width] = True
    return np.minimum(differs.argmax(axis=1), np.minimum(lengths[a], lengths[b]))


def intervals(prefixes: list[int], least: int) -> list[tuple[int, int, int]]:
    """Intervals (first, last + 1, depth) of the common-prefix tree with a depth of ``least`` or more.

    ``prefixes[i]`` is what suffixes i and i + 1 have in common.
    """
    out: list[tuple[int, int, int]] = []
    stack: list[tuple[int, int]] = []  # open intervals: depth, first
    for i, depth in enumerate([*prefixes, -1]):
        first = i
        while stack and stack[-1][0] > depth:
            top, first = stack.pop()
            if top >= least:
                out.append((first, i + 1, top))
        if depth >= least and (not stack or stack[-1][0] < depth):
            stack.append((depth, first))
    return out


def repeats(before: list[bytes], after: list[bytes], length: int, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Interval, member, left extension, depth and left diversity, for each member of each interval.

    The extension is the longest that another member shares; diversity tells whether the left contexts
    of the interval differ at once, so that it is a maximal repeat as it stands.
    """
    order = np.array(sorted(range(len(after)), key=after.__getitem__))
    rights, n_right = _matrix(after, length)
    lefts, n_left = _matrix([b[::-1] for b in before], length)
    rank = np.empty(len(order), np.int64)
    rank[sorted(range(len(before)), key=lambda i: before[i][::-1])] = np.arange(len(order))
    pairs = np.arange(len(order) - 1) if len(order) else np.zeros(0, np.int64)
    prefix = [d for i in range(0, len(pairs), CHUNK) for d in common(rights, n_right, order[pairs[i : i + CHUNK]], order[pairs[i : i + CHUNK] + 1]).tolist()]
    tree = intervals(prefix, least)
    out = []
    at = 0
    while at < len(tree):
        to, total = at, 0
        while to < len(tree) and (to == at or total + tree[to][1] - tree[to][0] <= CHUNK):
            total += tree[to][1] - tree[to][0]
            to += 1
        sizes = np.array([b - a for a, b, _ in tree[at:to]])
        node = np.repeat(np.arange(at, to), sizes)
        member = np.concatenate([order[a:b] for a, b, _ in tree[at:to]])
        depth = np.repeat(np.array([d for _, _, d in tree[at:to]]), sizes)
        by = np.lexsort((rank[member], node))
        node, member, depth = node[by], member[by], depth[by]
        shared = np.where(node[1:] == node[:-1], common(lefts, n_left, member[:-1], member[1:]), -1)
        extension = np.maximum(np.append(shared, -1), np.append(-1, shared))
        inner = np.where(shared < 0, length, shared)
        least_shared = np.minimum.reduceat(np.append(inner, length), np.cumsum(np.append(0, sizes[:-1])))
        out.append((node, member, extension, depth, np.repeat(least_shared == 0, sizes)))
        at = to
    if not out:
        return (np.zeros(0, np.int64),) * 4 + (np.zeros(0, bool),)
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def shard_index(table: pa.Table, length: int, gram: int) -> dict[str, np.ndarray]:
    """Spans of regions that stand for themselves alone: where another region repeats them."""
    before, after = table["before"].to_pylist(), table["after"].to_pylist()
    _, member, extension, depth, _ = repeats(before, after, length, gram)
    alone = ~table["covered"].to_numpy()
    keep = (extension >= 0) & (extension + depth >= length)
    keep &= alone[member] if len(member) else keep
    member = member[keep]
    return {"gram": table["gram"].to_numpy()[member], "region": table["region"].to_numpy()[member], "start": -extension[keep].astype(np.int32), "stop": depth[keep].astype(np.int32)}


def units(length: int = LENGTH) -> Units:
    return Units(length, max(1, length // 4))


def _spans(docs: DataFrame, length: int):
    docs, keys = keys_of(docs)
    u = units(length)
    return docs, keys, u, repeat_spans(docs, u, keys, partial(shard_index, length=length, gram=u.gram), ordered=False)


def removal_report(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256: each byte of a repeated window goes."""
    docs, keys, u, spans = _spans(docs.select("doc_id", "text"), length)
    return apply_spans(docs, spans, keys, u, keep_text=False).toDF("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def remove_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """The documents without repeated windows; a character that a cut splits goes as a whole; n_chars is counted anew.

    Other columns may have any names.
    """
    marked, keys, u, spans = _spans(plainly_named(docs), length)
    out = apply_spans(marked, spans, keys, u, keep_text=True).toDF(*docs.columns)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.char_length("text").cast(dict(docs.dtypes)["n_chars"]))
    return out.select(*(F.col(f"`{c}`") for c in docs.columns))


def removed_runs(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, start, stop of every maximal removed run."""
    marked, keys, _, spans = _spans(docs.select("doc_id", "text"), length)
    pieces = marked.select("doc_id", *keys).join(spans, keys).select("doc_id", *keys, F.explode(F.arrays_zip("__starts", "__stops")).alias("s"))
    own = W.partitionBy(*keys).orderBy("start", "stop")
    pieces = pieces.select("doc_id", *keys, F.col("s.__starts").alias("start"), F.col("s.__stops").alias("stop"))
    pieces = pieces.withColumn("reach", F.max("stop").over(own.rowsBetween(W.unboundedPreceding, -1)))
    pieces = pieces.withColumn("run", F.count_if((F.col("start") > F.col("reach")) | F.col("reach").isNull()).over(own))
    return pieces.groupBy("doc_id", *keys, "run").agg(F.min("start").alias("start"), F.max("stop").alias("stop")).select("doc_id", "start", "stop")


GROUPS = "gram long, region long, group string, start int, stop int"


def _groups(length: int, gram: int):
    """Maximal repeats of a shard: members, and where the repeat lies around each member's anchor.

    An interval of the tree is as deep as its members agree to the right.  Its members in the order of their
    left contexts form a tree of the same kind: each interval of that one is a group that agrees so far to the
    left and no further, so it cannot be extended for all.  A group whose members lie in one child of the first
    interval agrees further to the right and is reported there.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if len(b)]
        if not held:
            return
        table = pa.Table.from_batches(held)
        before, after = table["before"].to_pylist(), table["after"].to_pylist()
        node, member, extension, depth, _ = repeats(before, after, length, gram)
        grams, regions = table["gram"].to_numpy(), table["region"].to_numpy()
        cuts = np.flatnonzero(np.append(True, node[1:] != node[:-1])) if len(node) else np.zeros(0, np.int64)
        out: dict[tuple, tuple[int, int, list[int]]] = {}
        for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(node)], strict=True):
            own, deep = member[a:b].tolist(), int(depth[a])
            lefts = [before[m][::-1] for m in own]
            shared = [_agree(x, y) for x, y in zip(lefts, lefts[1:])]
            for first, last, back in [*intervals(shared, max(1, length - deep)), *([(0, len(own), 0)] if deep >= length and min(shared) == 0 else [])]:
                some = own[first:last]
                if len({after[m][deep : deep + 1] for m in some}) > 1 or any(len(after[m]) == deep for m in some):
                    text = before[some[0]][len(before[some[0]]) - back :] + after[some[0]][:deep]
                    out[blake2b(text, digest_size=16).hexdigest(), int(grams[some[0]])] = (back, deep, some)
        rows = [(int(grams[m]), int(regions[m]), g, -back, deep) for (g, _), (back, deep, some) in out.items() for m in some]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), (pa.int64(), pa.int64(), pa.string(), pa.int32(), pa.int32()))], names=["gram", "region", "group", "start", "stop"])

    return run


def _agree(x: bytes, y: bytes) -> int:
    n = min(len(x), len(y))
    return next((i for i in range(n) if x[i] != y[i]), n)


def repeat_groups(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """group, doc_id, start, stop: the maximal repeats of ``length`` bytes or more with all their occurrences.

    Repeats are seen in a region of one anchor, ``length`` bytes to each side; a longer one is a chain of groups,
    one for each anchor in it.  Regions that are equal as a whole are a group as well.
    """
    marked, keys = keys_of(docs.select("doc_id", "text"))
    u = units(length)
    rows = written(repeated(written(anchor_table(marked, u, keys), "all-anchors"), keys, False), "anchors")
    found = written(regions(rows.where("several and chosen"), marked, u, keys), "regions")
    grouped = found.repartition(partitions_for(docs.sparkSession, found.count(), SHARD_ROWS), "gram").mapInArrow(_groups(length, u.gram), GROUPS)
    members = rows.where(F.col("several")).join(grouped, ["gram", "region"])
    size = marked.select(*keys, F.octet_length(F.coalesce("text", F.lit(""))).alias("n"))
    back, ahead = F.greatest(F.col("place") + F.lit(u.gram - length), F.lit(0)) - F.col("place"), F.least(F.col("place") + F.lit(length), F.col("n")) - F.col("place")
    alike = rows.where("covered").join(size, keys).where(F.col("chosen") | F.lit(True))
    name = F.concat_ws("-", F.lit("region"), F.hex("gram"), F.hex("region"))
    whole = alike.select(name.alias("group"), *keys, (F.col("place") + back).alias("start"), (F.col("place") + ahead).alias("stop"))
    parts = members.select("group", *keys, (F.col("place") + F.col("start")).alias("start"), (F.col("place") + F.col("stop")).alias("stop"))
    ids = marked.select("doc_id", *keys).distinct()
    return whole.unionByName(parts).distinct().join(ids, keys).select("group", "doc_id", F.col("start").cast("long").alias("start"), F.col("stop").cast("long").alias("stop"))


def op6(docs: DataFrame) -> DataFrame:
    return removal_report(docs)
