"""Substring deduplication over words, by a compressed FM-index per shard.

A shard's regions are joined to one string, its suffixes sorted, and the last column kept in a wavelet
tree (in the layout that stores each level as one bit string with counts), beside a sample of the
suffix array.  Then the regions are streamed against the index: backward search runs for a run of
positions at once, each step adds a word to the left and maps the interval of matching suffixes; a
position drops out when only it itself is left.  What remains after ``length`` steps are the intervals
above the threshold; their rows are walked back to sampled suffixes, which tell the documents, and the
least document of each interval decides.

Odd input: null texts have no words; texts shorter than a window keep all words; rows that repeat an
id are not smaller than each other; null ids come before all others; an empty table gives an empty
result.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .anchors import Units, apply_spans, keys_of, plainly_named, repeat_spans

LENGTH, GRAM = 13, 5


class BitString:
    """Bits with constant-time rank: 64 to a word, and the ones before each word."""

    def __init__(self, bits: np.ndarray):
        n = len(bits)
        padded = np.zeros((n // 64 + 1) * 64, np.uint8)
        padded[:n] = bits
        self.words = np.packbits(padded, bitorder="little").view(np.uint64)
        self.before = np.zeros(len(self.words), np.int32)
        np.cumsum(np.bitwise_count(self.words[:-1]), out=self.before[1:])

    def at(self, i: np.ndarray) -> np.ndarray:
        """Whether each place has a one."""
        return (self.words[i >> 6] >> (i & 63).astype(np.uint64)) & np.uint64(1) > 0

    def ones(self, i: np.ndarray) -> np.ndarray:
        """Ones before each place."""
        word = i >> 6
        mask = (np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[word] + np.bitwise_count(self.words[word] & mask)


class WaveletTree:
    """Occurrences of a symbol before a place, over a string of numbers below ``size``."""

    def __init__(self, symbols: np.ndarray, size: int):
        self.bits = max(1, int(size - 1).bit_length())
        self.levels: list[tuple[BitString, int]] = []
        for level in range(self.bits - 1, -1, -1):
            one = ((symbols >> level) & 1).astype(np.uint8)
            self.levels.append((BitString(one), int(len(one) - one.sum())))
            symbols = np.concatenate([symbols[one == 0], symbols[one == 1]])
        self.first = self._down(np.arange(size), np.zeros(size, np.int64))

    def _down(self, symbol: np.ndarray, place: np.ndarray) -> np.ndarray:
        for level, (bits, zeros) in zip(range(self.bits - 1, -1, -1), self.levels, strict=True):
            ones = bits.ones(place)
            place = np.where((symbol >> level) & 1, zeros + ones, place - ones)
        return place

    def rank(self, symbol: np.ndarray, place: np.ndarray) -> np.ndarray:
        return self._down(symbol, place) - self.first[symbol]

    def symbol(self, place: np.ndarray) -> np.ndarray:
        """The symbol at each place."""
        out = np.zeros(len(place), np.int64)
        for level, (bits, zeros) in zip(range(self.bits - 1, -1, -1), self.levels, strict=True):
            ones, one = bits.ones(place), bits.at(place)
            out |= one.astype(np.int64) << level
            place = np.where(one, zeros + ones, place - ones)
        return out


#: Every so many-th place of a string keeps its suffix's row; others are found by walking back.
SAMPLED = 4
#: Places of streamed documents that are searched for at once.
STREAM = 1 << 18


class FMIndex:
    """A compressed index of strings of symbols from 1 on; each string ends in a separator of its own.

    What it keeps is the wavelet tree of the last column, the counts below each symbol, and the strings of the
    sampled suffixes with one bit for each row; neither the strings nor the suffix array.
    """

    def __init__(self, symbols: np.ndarray, owner: np.ndarray, strings: int, longest: int):
        """``symbols`` has a 0 after each string; ``owner`` is the string of each place."""
        n = len(symbols)
        self.n, self.size = n, int(symbols.max(initial=0)) + 1
        rank = np.where(symbols == 0, owner, symbols.astype(np.int64) + strings)
        step = 1
        while True:
            following = np.zeros(n, np.int64)
            following[: n - step] = rank[step:] + 1
            code = rank * np.int64(2 * n + strings + self.size + 2) + following
            values, rank = np.unique(code, return_inverse=True)
            step *= 2
            if len(values) == n or step > 2 * (longest + 1):
                break
        suffixes = np.argsort(rank, kind="stable")
        self.tree = WaveletTree(symbols[suffixes - 1], self.size)
        self.below = np.zeros(self.size + 1, np.int64)
        np.cumsum(np.bincount(symbols, minlength=self.size), out=self.below[1:])
        # the first place of each string is among the sampled ones, so no walk leaves its string
        start = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
        sampled = ((np.arange(n) - start[owner]) % SAMPLED == 0)[suffixes]
        self.marks, self.samples = BitString(sampled.astype(np.uint8)), owner[suffixes[sampled]].astype(np.int32)

    def extend(self, symbol: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The interval of each pattern with a symbol put before it."""
        return self.below[symbol] + self.tree.rank(symbol, low), self.below[symbol] + self.tree.rank(symbol, high)

    def strings_of(self, rows: np.ndarray) -> np.ndarray:
        """The string that the suffix of each row is in: walks back to a sampled suffix."""
        out = np.empty(len(rows), np.int32)
        open_, at = np.arange(len(rows)), rows.copy()
        while len(open_):
            known = self.marks.at(at)
            out[open_[known]] = self.samples[self.marks.ones(at[known])]
            open_, at = open_[~known], at[~known]
            symbol = self.tree.symbol(at)
            at = self.below[symbol] + self.tree.rank(symbol, at)
        return out

    def matches(self, symbols: np.ndarray, ends: np.ndarray, length: int, least: int = 2) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Matching statistics up to ``length``: for each end in a stream of symbols how far back ``least`` suffixes agree, and the interval."""
        low, high = np.zeros(len(ends), np.int64), np.full(len(ends), self.n)
        reach = np.zeros(len(ends), np.int64)
        alive = np.arange(len(ends))
        for step in range(1, length + 1):
            at = ends[alive] - step
            alive, at = alive[at >= 0], at[at >= 0]
            symbol = symbols[at]
            alive, symbol = alive[symbol > 0], symbol[symbol > 0]
            a, b = self.extend(symbol, low[alive], high[alive])
            on = b - a >= least
            alive = alive[on]
            low[alive], high[alive], reach[alive] = a[on], b[on], step
        return reach, low, high


def shard_index(table: pa.Table, length: int) -> dict[str, np.ndarray]:
    """Windows of regions that also start in a region of a smaller document.

    The index is built of the shard's regions; then they are streamed against it, ``STREAM`` places at a time.
    """
    before, after = table["before"].to_pylist(), table["after"].to_pylist()
    n_before = np.array([len(x) // 8 for x in before])
    sizes = n_before + np.array([len(x) // 8 for x in after])
    owner = np.repeat(np.arange(len(sizes)), sizes + 1)
    stops = np.cumsum(sizes + 1)
    hashes = np.frombuffer(b"".join(x + y + bytes(8) for x, y in zip(before, after, strict=True)), np.uint64)
    values = np.unique(hashes)
    symbols = np.searchsorted(values, hashes) + 1
    symbols[stops - 1] = 0
    index = FMIndex(symbols, owner, len(sizes), int(sizes.max()))
    ids = table["id"].to_numpy()
    place = np.arange(len(symbols)) - (stops - sizes - 1)[owner]
    every = np.flatnonzero((place >= length - 1) & (symbols > 0)) + 1
    known: dict[int, int] = {}  # first row of an interval met before -> the least document of it
    hits = []
    for i in range(0, len(every), STREAM):
        ends = every[i : i + STREAM]
        reach, low, high = index.matches(symbols, ends, length)
        full = reach == length
        ends, low, high = ends[full], low[full], high[full]
        if not len(ends):
            continue
        # intervals of one depth are equal or apart: each is looked up once
        first, at, back = np.unique(low, return_index=True, return_inverse=True)
        new = np.array([x not in known for x in first.tolist()])
        if new.any():
            starts, counts = first[new], (high[at] - first)[new]
            rows = np.repeat(starts - (np.cumsum(counts) - counts), counts) + np.arange(counts.sum())
            least = np.minimum.reduceat(ids[index.strings_of(rows)], np.cumsum(counts) - counts)
            known.update(zip(starts.tolist(), least.tolist(), strict=True))
        least = np.array([known[x] for x in first.tolist()])[back]
        hits.append(ends[least < ids[owner[ends - 1]]])
    ends = np.concatenate(hits) if hits else every[:0]
    at = owner[ends - 1]
    start = (place[ends - 1] + 1 - length - n_before[at]).astype(np.int32)
    return {"gram": table["gram"].to_numpy()[at], "region": table["region"].to_numpy()[at], "start": start, "stop": start + np.int32(length)}


def _spans(docs: DataFrame, length: int):
    docs, keys = keys_of(docs)
    u = Units(length, min(GRAM, length), words=True)
    return docs, keys, u, repeat_spans(docs, u, keys, partial(shard_index, length=length), ordered=True)


def removal_report(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256: each word of a window that a smaller document has goes."""
    docs, keys, u, spans = _spans(docs.select("doc_id", "text"), length)
    found = apply_spans(docs, spans, keys, u, keep_text=False)
    return found.select("doc_id", F.col("__units").alias("n_words"), F.col("__removed").alias("n_removed"), F.col("__sha256").alias("kept_sha256"))


def remove_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """The documents without such words; where words go, the others are joined by single spaces.  Other columns may have any names."""
    marked, keys, u, spans = _spans(plainly_named(docs), length)
    return apply_spans(marked, spans, keys, u, keep_text=True).toDF(*docs.columns)


def op7(docs: DataFrame) -> DataFrame:
    return removal_report(docs)
