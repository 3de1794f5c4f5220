"""Repeated windows of bytes or words: finding, routing and removing them.

A window is ``length`` consecutive units (bytes or words) of one text.  Equal windows choose the same
place in themselves, their anchor: the start of the short gram with the least hash.  So texts need to
be compared only around anchors whose gram occurs more than once, and there they are already aligned.

1. ``anchor_table``: a pass over the texts; for each anchor the hash of its gram, the digest of its
   region (all windows that hold it) and its place.
2. ``repeated``: one exchange by gram; anchors that occur once go.  Where whole regions are equal,
   nothing needs comparing: copies collapse here, however many there are.  Heavy grams (``skew.py``)
   are counted by partial sums instead.
3. ``regions``: one representative of each distinct region whose gram also has other regions; its
   content is fetched from the texts.
4. An index of each shard of regions (suffix array or FM-index, see the modules that call this) tells
   which parts of them are repeated.  A gram with more than ``HOT`` distinct regions would not fit a
   shard: for it, digests of all windows are counted instead, spread over all tasks.
5. ``apply_spans``: spans are gathered by document and taken out.

``Units`` says what a window is; all steps work on whole texts.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .skew import SHARES, heavy_keys
from .storage import partitions_for, written
from .textblocks import BYTE_SEED, PLAIN_WORDS, WORD_SEED, Block, Words, blocks, digests, grams, mix, owners, window_minima

#: Distinct regions of one gram beyond which they are compared by window digests, not in one shard.
HOT = 20_000
#: Regions in a shard, about.
SHARD_ROWS = 40_000
NO_ID = -(1 << 63)


@dataclass(frozen=True)
class Units:
    length: int  # of a window
    gram: int
    words: bool = False

    def sequence(self, block: Block) -> tuple[np.ndarray, np.ndarray]:
        """The units of a block as numbers, and where each text's begin."""
        if not self.words:
            return block.data, block.offsets
        words = Words(block, PLAIN_WORDS)
        return words.hashes, words.offsets

    @property
    def item(self) -> np.dtype:
        return np.dtype(np.uint64 if self.words else np.uint8)


def anchors(block: Block, units: Units) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text, place (from the text's start), gram hash and region digest of each anchor."""
    values, offsets = units.sequence(block)
    width = units.length - units.gram + 1
    hashed = grams(values, units.gram)
    none = np.zeros(0, np.int64)
    if len(hashed) < width:
        return none, none, none, none
    low = (1 << max(24, len(hashed).bit_length())) - 1
    packed = (hashed & np.uint64(~low & 0xFFFFFFFFFFFFFFFF)) | np.arange(len(hashed), dtype=np.uint64)
    least = window_minima(packed, width)
    text = owners(offsets)
    starts = np.arange(len(least))
    fits = starts + units.length <= offsets[1:][text[: len(least)]]
    places = (least[fits] & np.uint64(low)).astype(np.int64)
    if not len(places):
        return none, none, none, none
    places = places[np.append(True, places[1:] != places[:-1])]
    text = text[places]
    left = np.maximum(offsets[text], places + units.gram - units.length)
    right = np.minimum(offsets[text + 1], places + units.length)
    digest = mix(digests(values, left, right) + (places - left).astype(np.uint64) * np.uint64(WORD_SEED))
    return text, places - offsets[text], hashed[places].view(np.int64), digest.view(np.int64)


def plainly_named(docs: DataFrame) -> DataFrame:
    """The documents with columns, other than id and text, under names that nothing here uses."""
    return docs.toDF(*(c if c in ("doc_id", "text") else f"column_{i}" for i, c in enumerate(docs.columns)))


def keys_of(docs: DataFrame) -> tuple[DataFrame, list[str]]:
    """The documents with columns that tell rows apart by what they are, and the names of these columns.

    Ids do, unless some are repeated or null; then a checksum of the text joins them.
    """
    docs = docs.withColumn("__id", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)))
    odd = docs.groupBy("__id").agg(F.count("*").alias("n")).where((F.col("n") > 1) | (F.col("__id") == NO_ID)).limit(1).count()
    return docs.withColumn("__sum", F.xxhash64("text") if odd else F.lit(0).cast("long")), ["__id", "__sum"] if odd else ["__id"]


def anchor_table(docs: DataFrame, units: Units, keys: list[str]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = [batch.column(k).to_numpy() for k in keys]
            for block in blocks(batch.column("text"), 1 << 20):
                text, place, gram, digest = anchors(block, units)
                yield pa.RecordBatch.from_arrays([*(pa.array(x[block.first + text]) for x in ids), pa.array(place.astype(np.int32)), pa.array(gram), pa.array(digest)], names=[*keys, "place", "gram", "region"])

    return docs.select(*keys, "text").mapInArrow(run, ", ".join(f"{k} long" for k in keys) + ", place int, gram long, region long")


def repeated(table: DataFrame, keys: list[str], ordered: bool) -> DataFrame:
    """Anchors whose gram occurs again, with what is known of them.

    ``covered``: the whole region is repeated (``ordered``: in a row of a smaller id).  ``several``: the
    gram has other regions too.  ``chosen``: this row stands for its region.

    Heavy grams are counted with partial sums in each task; what is known of them comes back by broadcast.
    """
    total = table.count()
    heavy = written(heavy_keys(table, "gram", total), "heavy-grams")
    if not heavy.limit(1).count():
        return _repeated_here(table, keys, ordered)
    rest = table.join(F.broadcast(heavy), "gram", "left_anti")
    often = table.join(F.broadcast(heavy), "gram", "left_semi")
    return _repeated_here(rest, keys, ordered).union(_repeated_often(often, keys, ordered, total))


def _repeated_here(table: DataFrame, keys: list[str], ordered: bool) -> DataFrame:
    """``repeated`` by one exchange: all anchors of a gram meet in one task."""
    same = W.partitionBy("gram", "region")
    rows = table.withColumn("of_gram", F.count("*").over(W.partitionBy("gram"))).where("of_gram > 1")
    rows = rows.withColumn("of_region", F.count("*").over(same)).withColumn("least", F.min("__id").over(same))
    rows = rows.withColumn("chosen", F.row_number().over(same.orderBy(*keys, "place")) == 1)
    covered = F.col("__id") > F.col("least") if ordered else F.col("of_region") > 1
    return rows.select(*keys, "place", "gram", "region", covered.alias("covered"), (F.col("of_gram") > F.col("of_region")).alias("several"), "chosen")


def _repeated_often(table: DataFrame, keys: list[str], ordered: bool, total: int) -> DataFrame:
    """``repeated`` for the few heavy grams: regions are counted with partial sums and joined back.

    Regions with many rows are few as well and are broadcast; the others meet by region.  The row that
    stands for a region comes once more, from the counts, as the only chosen one.
    """
    by_region = table.groupBy("gram", "region").agg(F.count("*").alias("of_region"), F.min(F.struct(*keys, "place")).alias("first"))
    by_region = written(by_region, "heavy-regions")
    by_gram = by_region.groupBy("gram").agg(F.sum("of_region").alias("of_gram"))
    by_region = by_region.join(F.broadcast(by_gram), "gram").withColumn("least", F.col("first.__id"))
    big = F.col("of_region") > max(1, total // SHARES)
    known = by_region.drop("first")
    few = known.where(big)
    rows = table.join(F.broadcast(few), ["gram", "region"]).unionByName(table.join(F.broadcast(few.select("gram", "region")), ["gram", "region"], "left_anti").join(known.where(~big), ["gram", "region"]))
    covered = F.col("__id") > F.col("least") if ordered else F.col("of_region") > 1
    several = F.col("of_gram") > F.col("of_region")

    def shaped(df: DataFrame, chosen: bool) -> DataFrame:
        return df.where("of_gram > 1").select(*keys, "place", "gram", "region", covered.alias("covered"), several.alias("several"), F.lit(chosen).alias("chosen"))

    return shaped(rows, False).union(shaped(by_region.select("gram", "region", "of_region", "of_gram", "least", "first.*"), True))


def regions(chosen: DataFrame, docs: DataFrame, units: Units, keys: list[str]) -> DataFrame:
    """Content of regions, to the left and to the right of the anchor's start."""
    wanted = chosen.groupBy(*keys).agg(F.collect_list("gram").alias("grams"), F.collect_list("region").alias("regions"), F.collect_list("place").alias("places"), F.collect_list("covered").alias("covered"))
    found = wanted.join(docs.select(*keys, "text").dropDuplicates(keys) if len(keys) > 1 else docs.select(*keys, "text"), keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("text"), 1 << 20):
                values, offsets = units.sequence(block)
                for i in range(len(block)):
                    at = block.first + i
                    own = values[offsets[i] : offsets[i + 1]]
                    places = batch.column("places")[at].values.to_numpy()
                    left = [own[max(0, p + units.gram - units.length) : p].tobytes() for p in places]
                    right = [own[p : p + units.length].tobytes() for p in places]
                    ids = np.full(len(places), batch.column("__id")[at].as_py(), np.int64)
                    yield pa.RecordBatch.from_arrays(
                        [batch.column("grams")[at].values, batch.column("regions")[at].values, pa.array(ids), batch.column("covered")[at].values, pa.array(left, pa.binary()), pa.array(right, pa.binary())],
                        names=["gram", "region", "id", "covered", "before", "after"],
                    )

    return found.mapInArrow(run, "gram long, region long, id long, covered boolean, before binary, after binary")


SPANS = "gram long, region long, start int, stop int"  # from the anchor's place


def _window_digests(units: Units):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(len(batch)):
                before = np.frombuffer(batch.column("before")[i].as_py(), units.item)
                whole = np.concatenate([before, np.frombuffer(batch.column("after")[i].as_py(), units.item)])
                n = len(whole) - units.length + 1
                one, two = grams(whole, units.length, BYTE_SEED), grams(whole, units.length, WORD_SEED)
                start = (np.arange(n) - len(before)).astype(np.int32)
                same = [pa.array(np.full(n, batch.column(c)[i].as_py(), np.int64)) for c in ("gram", "region", "id")]
                yield pa.RecordBatch.from_arrays([*same, pa.array(start), pa.array(one.view(np.int64)), pa.array(two.view(np.int64))], names=["gram", "region", "id", "start", "one", "two"])

    return run


def hot_spans(found: DataFrame, units: Units, ordered: bool) -> DataFrame:
    """Repeated windows of regions too many for a shard, by counting the digests of all their windows.

    Windows count as equal at the same place from equal grams only: one window that two regions hold
    is not its own repeat, and a repeated window lies alike around the anchor that it chooses.
    """
    windows = found.mapInArrow(_window_digests(units), "gram long, region long, id long, start int, one long, two long")
    counted = windows.groupBy("gram", "start", "one", "two").agg(F.count("*").alias("n"), F.min("id").alias("least")).where("n > 1")
    hit = windows.join(counted, ["gram", "start", "one", "two"])
    if ordered:
        hit = hit.where("id > least")
    return hit.select("gram", "region", "start", (F.col("start") + F.lit(units.length)).cast("int").alias("stop"))


def shard_spans(found: DataFrame, index: Callable[[pa.Table], dict[str, np.ndarray]], rows: int) -> DataFrame:
    """Runs an index over shards of regions; all regions of a gram are in one shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if len(b)]
        if held:
            out = index(pa.Table.from_batches(held))
            yield pa.RecordBatch.from_arrays([pa.array(out[c]) for c in ("gram", "region", "start", "stop")], names=["gram", "region", "start", "stop"])

    spark = found.sparkSession
    return found.repartition(partitions_for(spark, rows, SHARD_ROWS), "gram").mapInArrow(run, SPANS)


def repeat_spans(docs: DataFrame, units: Units, keys: list[str], index, ordered: bool, hot: int | None = None) -> DataFrame:
    """keys, __starts, __stops: for each document with repeated windows where they lie, as start and stop of units."""
    hot = HOT if hot is None else hot
    table = written(anchor_table(docs, units, keys), "all-anchors")
    rows = written(repeated(table, keys, ordered), "anchors")
    found = written(regions(rows.where("several and chosen"), docs, units, keys), "regions")
    many = found.groupBy("gram").agg(F.count("*").alias("n")).where(F.col("n") > hot).select("gram")
    hot_grams = written(many, "hot-grams")
    n = found.count()
    parts = shard_spans(found.join(F.broadcast(hot_grams), "gram", "left_anti"), index, n)
    if hot_grams.limit(1).count():
        parts = parts.union(hot_spans(found.join(F.broadcast(hot_grams), "gram", "left_semi"), units, ordered))
    parts = written(parts, "region-spans")
    whole = rows.where("covered").select(*keys, F.greatest(F.col("place") + F.lit(units.gram - units.length), F.lit(0)).alias("start"), (F.col("place") + F.lit(units.length)).alias("stop"))
    open_ = rows.where("several and not covered").join(parts, ["gram", "region"])
    open_ = open_.select(*keys, (F.col("place") + F.col("start")).alias("start"), (F.col("place") + F.col("stop")).alias("stop"))
    return whole.union(open_).groupBy(*keys).agg(F.collect_list("start").alias("__starts"), F.collect_list("stop").alias("__stops"))


def covered_units(n: int, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    """Which of n units lie in a span."""
    marks = np.zeros(n + 1, dtype=np.int64)
    np.add.at(marks, starts, 1)
    np.add.at(marks, np.minimum(stops, n), -1)
    return np.cumsum(marks[:-1]) > 0


def apply_spans(docs: DataFrame, spans: DataFrame, keys: list[str], units: Units, keep_text: bool) -> DataFrame:
    """The documents with what remains of them: digest columns, or the columns as they were with the text cut."""
    joined = docs.join(spans, keys, "left")
    names = [c for c in docs.columns if c not in ("__id", "__sum")]
    counted = ["__units", "__removed", "__runs", "__sha256"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict[str, list] = {c: [] for c in [*counted, "text"]}
            for block in blocks(batch.column("text"), 1 << 20):
                words = Words(block, PLAIN_WORDS, hashes=False) if units.words else None
                for i in range(len(block)):
                    at = block.first + i
                    starts = batch.column("__starts")[at]
                    n = int(words.counts()[i]) if words else int(block.offsets[i + 1] - block.offsets[i])
                    gone = covered_units(n, starts.values.to_numpy(), batch.column("__stops")[at].values.to_numpy()) if starts.is_valid else np.zeros(n, bool)
                    if words:
                        own = range(words.offsets[i], words.offsets[i + 1])
                        left = b" ".join(block.data[words.starts[w] : words.ends[w]].tobytes() for w, g in zip(own, gone.tolist(), strict=True) if not g)
                    else:
                        left = block.data[block.offsets[i] : block.offsets[i + 1]]
                        left = (left[~gone] if gone.any() else left).tobytes()
                    out["__units"].append(n)
                    out["__removed"].append(int(gone.sum()))
                    out["__runs"].append(int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if n else 0)
                    out["__sha256"].append(hashlib.sha256(left).hexdigest())
                    if keep_text:
                        valid = batch.column("text")[at].is_valid
                        # a cut may fall inside a character: what is left of it goes too
                        out["text"].append(left.decode("utf-8", "ignore") if gone.any() else batch.column("text")[at].as_py() if valid else None)
            columns = {c: batch.column(c) for c in names}
            if keep_text:
                columns["text"] = pa.array(out["text"], pa.string())
                yield pa.RecordBatch.from_arrays(list(columns.values()), names=names)
            else:
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string()]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(out[c], k) for c, k in zip(counted, kinds, strict=True))], names=["doc_id", *counted])

    if keep_text:
        return joined.select(*names, "__starts", "__stops").mapInArrow(run, docs.select(*names).schema)
    return joined.select("doc_id", "text", "__starts", "__stops").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, __units long, __removed long, __runs long, __sha256 string")
