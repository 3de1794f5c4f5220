"""Benchmark decontamination by suffix arrays over the training texts.

Each block of training texts is a shard with its own suffix array over words.  Every test suffix is
binary-searched in every shard: the interval that its first ``width`` words meet gives all verbatim
occurrences, and where they go on beyond that they are followed word by word, so the longest match of
each test suffix and all its places are known.  Only training suffixes that start with two words that
also start a test suffix can match, so the array holds those alone, and only test suffixes whose two
words occur in the shard are looked up: nothing that could match is left out.  No row is exchanged.

* ``with_hits``, ``contamination``, ``decontaminate``: what windows of test items cover.
* ``verbatim_matches``: every maximal match with its place in item and document.
* ``longest_matches``: for each test suffix the longest of them.

The test side goes to the workers as a broadcast of at most ``MAX_TEST_BYTES`` of text; a larger test
set is worked off in blocks of that size, one pass over the training texts each.

Results for odd input: a null text has no words; an item without words matches nothing; equal items
with different ids are all reported; an item whose id is null marks words, but is not listed among the
items; repeated rows are each reported; columns of the documents may have any name; an empty table
gives an empty result or, on the test side, documents without hits.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .storage import written
from .textblocks import ALNUM_WORDS, Block, Words, blocks, owners

MAX_TEST_BYTES = 8 << 20
WIDTH = 10


def _ranges(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places of all ranges, one after the other."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)


def _member(sorted_values: np.ndarray, x: np.ndarray) -> np.ndarray:
    if not len(sorted_values):
        return np.zeros(len(x), bool)
    return sorted_values[np.minimum(np.searchsorted(sorted_values, x), len(sorted_values) - 1)] == x


def _packed(keys: np.ndarray) -> np.ndarray:
    """Rows of word ids as byte strings of the same order."""
    kind = f"S{4 * keys.shape[1]}"
    return np.ascontiguousarray(keys.astype(">u4")).view(kind).ravel() if len(keys) else np.zeros(0, kind)


def _windows(ids: np.ndarray, at: np.ndarray, rest: np.ndarray, width: int) -> np.ndarray:
    """The ``width`` word ids from each place on, 0 beyond the text it is in and after an unknown word."""
    inside = np.arange(width) < rest[:, None]
    keys = np.where(inside, np.append(ids, np.zeros(width, ids.dtype))[at[:, None] + np.arange(width)], 0)
    keys[np.maximum.accumulate(keys == 0, axis=1)] = 0
    return keys


@dataclass
class TestSuffixes:
    """The suffixes of all test items over their own vocabulary, and the windows that contaminate."""

    names: np.ndarray  # item ids as strings, None where it is null
    vocabulary: np.ndarray  # sorted word hashes; the id of a word is its place plus 1
    ids: np.ndarray  # word ids of all items, one after the other
    offsets: np.ndarray
    keys: np.ndarray  # distinct windows, sorted as byte strings
    lengths: np.ndarray  # words of each
    window_starts: np.ndarray  # window -> items, as ranges of window_items
    window_items: np.ndarray
    width: int

    @classmethod
    def of(cls, names: list[str | None], texts: list[str | None], width: int) -> TestSuffixes:
        block = next(blocks(pa.array(texts, pa.large_string()), 1 << 62), None)
        words = Words(block, ALNUM_WORDS, lower=True) if block else None
        hashes, offsets = (words.hashes, words.offsets) if words else (np.zeros(0, np.uint64), np.zeros(1, np.int64))
        vocabulary, ids = np.unique(hashes, return_inverse=True)
        ids = ids.astype(np.int64) + 1
        item, at = owners(offsets), np.arange(len(ids))
        rest = offsets[1:][item] - at
        whole = (rest >= width) | (at == offsets[:-1][item])  # an item of fewer words is one window
        keys, item = _windows(ids, at[whole], np.minimum(rest[whole], width), width), item[whole]
        packed, back = np.unique(_packed(keys), return_inverse=True)
        pairs = np.unique(back.astype(np.int64) * max(1, len(names)) + item)
        distinct = packed.view(">u4").reshape(-1, width).astype(np.int64) if len(packed) else np.zeros((0, width), np.int64)
        starts = np.searchsorted(pairs // max(1, len(names)), np.arange(len(packed) + 1))
        return cls(np.array([*names, None], dtype=object)[:-1], vocabulary, ids, offsets, distinct, (distinct > 0).sum(axis=1), starts, pairs % max(1, len(names)), width)

    def prepared(self) -> TestSuffixes:
        """What every search needs, made once on each worker."""
        if not hasattr(self, "step"):
            self.step = len(self.vocabulary) + 1
            self.heads = self.keys[:, 0] * self.step + (self.keys[:, 1] if self.width > 1 else 0)  # sorted, as the keys are
            self.low = _packed(self.keys)
            self.high = _packed(np.where(np.arange(self.width) >= self.lengths[:, None], 0xFFFFFFFF, self.keys))
            self.singles = np.unique(self.keys[self.lengths == 1, 0])
            # the same for all suffixes, of which windows are some: for matches and their places
            item, at = owners(self.offsets), np.arange(len(self.ids))
            self.item, self.rest = item, self.offsets[1:][item] - at
            following = np.where(self.rest > 1, np.append(self.ids[1:], 0)[: len(at)], 0)
            code = self.ids * self.step + following
            self.by_head = np.argsort(code, kind="stable")
            self.suffix_heads = code[self.by_head]
        return self


class TrainingSuffixes:
    """The suffix array of a shard, of the suffixes that a test suffix can start."""

    def __init__(self, words: Words, tests: TestSuffixes):
        self.tests = tests.prepared()
        at = np.searchsorted(tests.vocabulary, words.hashes)
        self.ids = np.where(_member(tests.vocabulary, words.hashes), at + 1, 0)
        n, width = len(self.ids), tests.width
        self.text = owners(words.offsets)
        self.ends = words.offsets[1:][self.text]
        following = np.append(self.ids[1:], 0)[:n]
        following[np.arange(n) + 1 >= self.ends] = 0
        code = self.ids * tests.step + following
        fits = (self.ids > 0) & (following > 0) & _member(tests.suffix_heads, code) | _member(tests.singles, self.ids)
        places = np.flatnonzero(fits)
        keys = _packed(_windows(self.ids, places, self.ends[places] - places, width))
        order = np.argsort(keys, kind="stable")
        self.keys, self.places = keys[order], places[order]
        self.codes = np.unique(code[places])

    def windows(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Test windows that occur, and for each the interval of the suffix array that it is a prefix of."""
        t = self.tests
        first = np.searchsorted(t.heads, self.codes, "left")
        some = _ranges(first, np.searchsorted(t.heads, self.codes, "right") - first)
        if t.width > 1 and len(t.singles):
            some = np.union1d(some, np.flatnonzero(t.lengths == 1))
        low, high = np.searchsorted(self.keys, t.low[some], "left"), np.searchsorted(self.keys, t.high[some], "right")
        found = high > low
        return some[found], low[found], high[found]

    def matches(self, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Test suffix, training place and length of every match of ``least`` words or more that nothing extends.

        A match is reported from its first word, so a test suffix whose match began before is not repeated.
        """
        t, width = self.tests, self.tests.width
        first = np.searchsorted(t.suffix_heads, self.codes, "left")
        suffix = t.by_head[_ranges(first, np.searchsorted(t.suffix_heads, self.codes, "right") - first)]
        depth = min(width, least)
        suffix = suffix[t.rest[suffix] >= least]
        key = _windows(t.ids, suffix, np.minimum(t.rest[suffix], depth), width)
        low = np.searchsorted(self.keys, _packed(key), "left")
        high = np.searchsorted(self.keys, _packed(np.where(np.arange(width) >= depth, 0xFFFFFFFF, key)), "right")
        suffix, place = np.repeat(suffix, high - low), self.places[_ranges(low, high - low)]
        # where the words before agree as well, the match began there
        inside = (suffix > t.offsets[:-1][t.item[suffix]]) & (place > 0)
        inside[inside] = self.text[place[inside] - 1] == self.text[place[inside]]
        begun = inside.copy()
        begun[inside] = t.ids[suffix[inside] - 1] == self.ids[place[inside] - 1]
        suffix, place = suffix[~begun], place[~begun]
        length = np.full(len(suffix), depth)
        room = np.minimum(t.rest[suffix], self.ends[place] - place)
        on = np.flatnonzero(length < room)
        while len(on):
            on = on[t.ids[suffix[on] + length[on]] == self.ids[place[on] + length[on]]]
            length[on] += 1
            on = on[length[on] < room[on]]
        keep = length >= least
        return suffix[keep], place[keep], length[keep]


def search_block(block: Block, tests: TestSuffixes) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Word offsets, a hit flag for each word, and the places of items found, by text."""
    words = Words(block, ALNUM_WORDS, lower=True)
    array = TrainingSuffixes(words, tests)
    window, low, high = array.windows()
    at, sizes = array.places[_ranges(low, high - low)], high - low
    lengths = np.repeat(tests.lengths[window], sizes)
    marks = np.bincount(at, minlength=len(words.hashes) + 1) - np.bincount(at + lengths, minlength=len(words.hashes) + 1)
    found: list[np.ndarray] = [np.zeros(0, np.int64)] * len(block)
    if len(window):
        pairs = np.unique(array.text[at] * np.int64(len(tests.keys)) + np.repeat(window, sizes))
        text, window = pairs // len(tests.keys), pairs % len(tests.keys)
        sizes = tests.window_starts[window + 1] - tests.window_starts[window]
        items = tests.window_items[_ranges(tests.window_starts[window], sizes)]
        pairs = np.unique(np.repeat(text, sizes) * np.int64(len(tests.names)) + items)
        text, items = pairs // len(tests.names), pairs % len(tests.names)
        cuts = np.flatnonzero(np.diff(text)) + 1
        for d, own in zip(text[np.append(0, cuts)], np.split(items, cuts), strict=True):
            found[d] = own
    return words.offsets, np.cumsum(marks[:-1]) > 0, found


HITS, ITEMS, COUNT = "__hits", "__items", "__n_words"


def _free(names: list[str], *wanted: str) -> list[str]:
    """The names wanted, longer where a table has them already."""
    taken = {n.lower() for n in names}
    out = []
    for w in wanted:
        while w.lower() in taken:
            w = "_" + w
        out.append(w)
    return out


def _pass(shared, text: str, added: list[str], first: bool):
    """One pass over the texts: adds what a block of test items hits to what earlier blocks have hit."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tests = shared.value
        for batch in batches:
            counts, hits, items = [], [], []
            for block in blocks(batch.column(batch.schema.get_field_index(text))):
                offsets, hit, found = search_block(block, tests)
                counts += np.diff(offsets).tolist()
                for i in range(len(block)):
                    own = hit[offsets[i] : offsets[i + 1]]
                    hits.append(np.packbits(own).tobytes() if own.any() else b"")
                    items.append(sorted({x for x in tests.names[found[i]] if x is not None}) if len(found[i]) else [])
            names = [n for n in batch.schema.names if n not in added]
            if not first:
                before = batch.column(added[1]).to_pylist(), batch.column(added[2]).to_pylist()
                for i, (a, b) in enumerate(zip(*before, strict=True)):
                    if a and hits[i]:
                        hits[i] = (np.frombuffer(a, np.uint8) | np.frombuffer(hits[i], np.uint8)).tobytes()
                    hits[i] = hits[i] or a
                    items[i] = sorted({*items[i], *b})
            made = [pa.array(counts, pa.int64()), pa.array(hits, pa.binary()), pa.array(items, pa.list_(pa.string()))]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(n)) for n in names), *made], names=[*names, *added])

    return run


def _test_blocks(items: DataFrame, width: int, item_id: str, item_text: str, max_test_bytes: int):
    """The test items in blocks of bounded size, each as a broadcast."""
    items = items.select(F.col(item_id).cast("string").alias("id"), F.col(item_text).alias("text"))
    size = items.agg(F.sum(F.octet_length("text") + F.lit(16))).first()[0] or 0
    n = max(1, -(-size // max_test_bytes))
    for i in range(n):
        part = items if n == 1 else items.where(F.pmod(F.xxhash64("id", "text"), F.lit(n)) == i)
        rows = part.collect()
        yield i, n, items.sparkSession.sparkContext.broadcast(TestSuffixes.of([r["id"] for r in rows], [r["text"] for r in rows], width))


def _with_hits(docs: DataFrame, items: DataFrame, width: int, text: str, item_id: str, item_text: str, max_test_bytes: int) -> tuple[DataFrame, list[str]]:
    added = _free(docs.columns, COUNT, HITS, ITEMS)
    kinds = (T.LongType(), T.BinaryType(), T.ArrayType(T.StringType()))
    schema = T.StructType([*docs.schema.fields, *(T.StructField(n, k) for n, k in zip(added, kinds, strict=True))])
    for i, n, shared in _test_blocks(items, width, item_id, item_text, max_test_bytes):
        docs = docs.mapInArrow(_pass(shared, text, added, first=i == 0), schema)
        if i < n - 1:
            docs = written(docs, "decontamination")
    return docs, added


def with_hits(docs: DataFrame, items: DataFrame, width: int = WIDTH, text: str = "text", item_id: str = "item_id", item_text: str = "text", max_test_bytes: int = MAX_TEST_BYTES) -> DataFrame:
    """The documents with the columns ``__n_words``, ``__hits`` (a bit for each word, empty if none is hit) and ``__items``."""
    return _with_hits(docs, items, width, text, item_id, item_text, max_test_bytes)[0]


def contamination(docs: DataFrame, items: DataFrame, id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """A row for each document: id, n_words, n_hit, items (ids of the items found, sorted as strings)."""
    return with_hits(docs.select(id, text), items, text=text, **options).select(
        id, F.col(COUNT).alias("n_words"), _ones(F.col(HITS)).alias("n_hit"), F.col(ITEMS).alias("items")
    )


def _ones(bits):
    """The number of ones in a binary column."""
    digits = F.hex(bits)
    count = F.lit(0)
    for ones, kind in ((1, "[1248]"), (2, "[3569AC]"), (3, "[7BDE]"), (4, "F")):
        count = count + F.regexp_count(digits, F.lit(kind)) * ones
    return count.cast("long")


def decontaminate(docs: DataFrame, items: DataFrame, width: int = WIDTH, text: str = "text", item_id: str = "item_id", item_text: str = "text", max_test_bytes: int = MAX_TEST_BYTES) -> DataFrame:
    """The documents that hold no window of a test item; columns as they were."""
    found, (_, hits, _) = _with_hits(docs, items, width, text, item_id, item_text, max_test_bytes)
    return found.where(F.octet_length(hits) == 0).select(*[F.col(f"`{c}`") for c in docs.columns])


MATCHES = "item_id string, item_start int, doc_id {}, doc_start int, n_words int"


def verbatim_matches(docs: DataFrame, items: DataFrame, least: int = WIDTH, id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text", max_test_bytes: int = MAX_TEST_BYTES) -> DataFrame:
    """item_id, item_start, doc_id, doc_start, n_words: a row for each run of ``least`` (2 or more) words of an
    item that a document has verbatim and that neither side extends; starts are counted in words."""
    least = max(2, least)
    source = docs.select(F.col(id).alias("doc_id"), F.col(text).alias("text"))
    out = None
    for _, _, shared in _test_blocks(items, min(least, WIDTH), item_id, item_text, max_test_bytes):

        def run(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            tests = shared.value
            for batch in batches:
                for block in blocks(batch.column("text")):
                    words = Words(block, ALNUM_WORDS, lower=True)
                    array = TrainingSuffixes(words, tests)
                    suffix, place, length = array.matches(least)
                    own = array.text[place]
                    columns = [
                        pa.array(tests.names[tests.item[suffix]], pa.string()), pa.array((suffix - tests.offsets[tests.item[suffix]]).astype(np.int32)),
                        batch.column("doc_id").take(pa.array(block.first + own)), pa.array((place - words.offsets[own]).astype(np.int32)), pa.array(length.astype(np.int32)),
                    ]
                    yield pa.RecordBatch.from_arrays(columns, names=["item_id", "item_start", "doc_id", "doc_start", "n_words"])

        found = source.mapInArrow(run, MATCHES.format(dict(source.dtypes)["doc_id"]))
        out = found if out is None else out.union(found)
    return out


def longest_matches(docs: DataFrame, items: DataFrame, least: int = WIDTH, **options) -> DataFrame:
    """item_id, item_start, n_words, doc_id, doc_start: the longest match that covers each test suffix's start,
    from that start on; of equal ones that in the least document and place.  Partial sums come before the exchange."""
    found = verbatim_matches(docs, items, least, **options)
    every = found.withColumn("by", F.explode(F.sequence(F.lit(0), F.col("n_words") - F.lit(max(2, least)))))
    best = F.min_by(F.struct(F.col("n_words") - F.col("by"), "doc_id", F.col("doc_start") + F.col("by")), F.struct(-(F.col("n_words") - F.col("by")), "doc_id", F.col("doc_start") + F.col("by")))
    out = every.groupBy("item_id", (F.col("item_start") + F.col("by")).alias("item_start")).agg(best.alias("m"))
    return out.select("item_id", "item_start", F.col("m").getField("col1").alias("n_words"), F.col("m.doc_id").alias("doc_id"), F.col("m").getField("col3").alias("doc_start"))


def op10(docs: DataFrame, items: DataFrame) -> DataFrame:
    found = contamination(docs, items)
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
    )
