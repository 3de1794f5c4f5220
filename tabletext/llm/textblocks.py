"""Vectorised byte and word arithmetic over Arrow text columns.

A block is a run of whole texts laid end to end.  Texts are never cut: a text longer than the
target size is a block of its own, so memory is bounded by the target plus the longest text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from xxhash import xxh3_64_intdigest

BLOCK_BYTES = 2 << 20

#: Seeds of two independent hashes, and the factor that tells first from second where hashes are joined.
BYTE_SEED, WORD_SEED, JOIN = 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xA24BAED4963EE407
#: Bytes of a slice beyond which it is hashed on its own.
LONG = 512

_SPACE = frozenset([0x20, *range(0x09, 0x0E)])
#: byte -> is part of a word, for words that anything but ASCII white space makes
PLAIN_WORDS = np.array([b not in _SPACE for b in range(256)])
#: byte -> is part of a word, for words of ASCII letters, digits and all non-ASCII bytes
ALNUM_WORDS = np.array([b >= 0x80 or chr(b).isascii() and chr(b).isalnum() for b in range(256)])
#: A-Z to a-z, all other bytes as they are
LOWER_AZ = np.array([b + 32 if 65 <= b <= 90 else b for b in range(256)], dtype=np.uint8)


class Block:
    """Some texts as one byte array; ``offsets`` has one entry more than there are texts."""

    def __init__(self, first: int, data: np.ndarray, offsets: np.ndarray):
        self.first, self.data, self.offsets = first, data, offsets

    def __len__(self) -> int:
        return len(self.offsets) - 1

    def text(self, i: int) -> bytes:
        return self.data[self.offsets[i] : self.offsets[i + 1]].tobytes()


def blocks(column: pa.Array | pa.ChunkedArray, target: int = BLOCK_BYTES) -> Iterator[Block]:
    """Blocks of a string column; a null counts as an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "" if not pa.types.is_binary(column.type) else b"")
    column = column.cast(pa.large_binary())
    n = len(column)
    if not n:
        return
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + n + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, np.uint8)
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + target, side="right")) - 1)
        to = min(to, n)
        yield Block(at, data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at])
        at = to


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads all bits; works in place."""
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    x *= np.uint64(0xD6E8FEB86659FD93)
    x ^= x >> np.uint64(32)
    return x


def _eights(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on as one number, zeros beyond the end; a view of one byte a step."""
    padded = np.zeros(len(data) + 8, np.uint8)
    padded[: len(data)] = data
    return np.ndarray(len(data) + 1, "<u8", buffer=padded, strides=(1,))


#: n -> a mask of the n low bytes
_LOW = np.array([(1 << (8 * n)) - 1 for n in range(9)], dtype=np.uint64)


def digests(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A hash of each slice of an array of bytes or of 64-bit numbers.

    Eight bytes a step: each step adds them to what it has and spreads all bits, and the length is
    where it begins; so slices of one length differ in their hash if they differ in one step alone,
    and by chance otherwise.  Slices beyond ``LONG`` bytes are hashed one by one.
    """
    width = values.itemsize
    data = values.view(np.uint8)
    at, left = starts.astype(np.int64) * width, (ends - starts).astype(np.int64) * width
    out = mix(left.astype(np.uint64) + np.uint64(BYTE_SEED))
    for i in np.flatnonzero(left > LONG):
        out[i] = xxh3_64_intdigest(data[at[i] : at[i] + left[i]].tobytes(), BYTE_SEED)
    open_ = np.flatnonzero((left > 0) & (left <= LONG))
    eights = _eights(data)
    while len(open_):
        here = eights[at[open_]]
        here &= _LOW[np.minimum(left[open_], 8)]
        here ^= out[open_]
        out[open_] = mix(here)
        at[open_] += 8
        left[open_] -= 8
        open_ = open_[left[open_] > 0]
    return out


def grams(values: np.ndarray, k: int, seed: int = BYTE_SEED) -> np.ndarray:
    """The hash of each run of k neighbours, joined from the hashes of runs half as long."""
    n = len(values) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    if values.dtype == np.uint8:
        have = min(k, 8)
        out = _eights(values)[: len(values) - have + 1] & _LOW[have]
    else:
        have, out = 1, values.astype(np.uint64)
    out ^= np.uint64(seed)
    mix(out)
    while have < k:
        step = min(have, k - have)
        joined = out[: len(out) - step] * np.uint64(JOIN)
        joined += out[step:]
        out, have = mix(joined), have + step
    return out


class Words:
    """The words of a block: where each starts and ends, its hash, and where each text's begin."""

    def __init__(self, block: Block, kind: np.ndarray = PLAIN_WORDS, lower: bool = False, hashes: bool = True):
        data, offsets = block.data, block.offsets
        self.data = LOWER_AZ[data] if lower else data
        inside = kind[self.data]
        before = np.empty_like(inside)
        before[1:] = inside[:-1]
        before[:1] = False
        edges = offsets[:-1][offsets[:-1] < len(data)]
        before[edges] = False
        self.starts = np.flatnonzero(inside & ~before)
        after = np.empty_like(inside)
        after[:-1] = inside[1:]
        after[-1:] = False
        ends = offsets[1:] - 1
        after[ends[ends >= 0]] = False
        self.ends = np.flatnonzero(inside & ~after) + 1
        self.offsets = np.searchsorted(self.starts, offsets)
        self.hashes = digests(self.data, self.starts, self.ends) if hashes else None

    def counts(self) -> np.ndarray:
        return np.diff(self.offsets)


def window_minima(values: np.ndarray, width: int) -> np.ndarray:
    """The least value of each run of ``width`` neighbours."""
    n = len(values) - width + 1
    if n <= 0:
        return values[:0]
    least, have = values, 1
    while have * 2 <= width:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    return np.minimum(least[:n], least[width - have : width - have + n]) if have < width else least[:n]


def owners(offsets: np.ndarray) -> np.ndarray:
    """The index of the text that each position belongs to."""
    return np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
