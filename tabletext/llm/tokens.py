"""Token ids as the tokenizers library gives them, from the same vocabulary as byte-pair ranks.

The file with ranks is the twin of the JSON file.  Both give equal ids (a test holds them against
each other); the ranks do it in a third of the time.  Where the twin is missing, or for any other
vocabulary, the library of the file itself is used.

``columns`` encodes the texts of a block together.  The pattern that parts texts before bytes are paired looks
at white space, letters and punctuation only, so some borders are certain: before a single space or around a
single line feed between other characters, and between a letter and a full stop or comma.  What lies between such
borders is encoded once a block, however often it occurs (equality is that of 64-bit hashes and lengths).
"""

from __future__ import annotations

import base64
import hashlib
import os
from collections.abc import Callable, Iterable
from functools import lru_cache

import numpy as np

from .textblocks import Block, digests

DEFAULT = "byte_bpe_50k.json"


def vocabulary_path(name: str = DEFAULT) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


@lru_cache(maxsize=4)
def version(path: str) -> str:
    """Digest of the vocabulary file: another file is another tokenizer."""
    with open(path, "rb") as f:
        return hashlib.sha256(f.read()).hexdigest()


@lru_cache(maxsize=4)
def _byte_pairs(path: str):
    import json

    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f)}
    with open(path.removesuffix(".tiktoken") + ".json", encoding="utf-8") as f:
        special = {t["content"]: t["id"] for t in json.load(f)["added_tokens"] if t["special"]}
    encoding = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)
    return encoding, tuple(special)


@lru_cache(maxsize=4)
def _widths(path: str) -> np.ndarray:
    """Bytes of each token."""
    encoding, _ = _byte_pairs(path)
    known = {encoding.encode_single_token(x): len(x) for x in encoding.token_byte_values()}
    out = np.zeros(encoding.max_token_value + 1, np.int64)
    out[list(known)] = list(known.values())
    return out


def encoder(path: str) -> Callable[[Iterable[str]], Iterable[np.ndarray]]:
    """A function from texts to their ids, no special tokens added."""
    twin = path.removesuffix(".json") + ".tiktoken"
    if path.endswith("byte_bpe_50k.json") and os.path.exists(twin):
        encoding, special = _byte_pairs(twin)

        def ids(texts: Iterable[str]) -> Iterable[np.ndarray]:
            for text in texts:
                if any(s in text for s in special):
                    yield encoding.encode_to_numpy(text, allowed_special="all")
                else:
                    yield encoding.encode_to_numpy(text, disallowed_special=())

        return ids
    if path.endswith(".json"):
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)

        def ids(texts: Iterable[str]) -> Iterable[np.ndarray]:
            for text in texts:
                yield np.array(tokenizer.encode(text, add_special_tokens=False).ids, dtype=np.uint32)

        return ids
    import sentencepiece

    pieces = sentencepiece.SentencePieceProcessor(model_file=path)

    def ids(texts: Iterable[str]) -> Iterable[np.ndarray]:
        for text in texts:
            yield np.array(pieces.encode(text), dtype=np.uint32)

    return ids


_BYTE = np.arange(256)
_PLAIN = (_BYTE > 0x20) & (_BYTE < 0x7F)  # ASCII without white space and controls
_TWO = (_BYTE >= 0xC3) & (_BYTE < 0xE0)  # leads a character of two bytes that is no white space
_OPENS, _LETTER = _PLAIN | _TWO, np.array([chr(b).isascii() and chr(b).isalpha() for b in range(256)])
_SPACE, _LINE = 0x20, 0x0A
_STOP = np.isin(_BYTE, (ord("."), ord(",")))


def _closed(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Whether the character before each place is certainly no white space."""
    last = data[at - 1]
    return (at > 0) & (_PLAIN[last] | (last >= 0x80) & (at > 1) & _TWO[data[at - 2]])


def _borders(block: Block) -> np.ndarray:
    """Where texts may be parted without a change of their ids, the start of each text included."""
    data, size = block.data, len(block.data)
    first = np.zeros(size + 1, bool)
    first[block.offsets] = True
    at = np.flatnonzero((data == _SPACE) | (data == _LINE))
    at = at[(at > 0) & (at + 1 < size)]
    at = at[_closed(data, at) & _OPENS[data[at + 1]] & ~first[at] & ~first[at + 1]]
    stops = np.flatnonzero(_STOP[data[1:]] & _LETTER[data[:-1]]) + 1
    first[at] = first[stops] = True
    first[at[data[at] == _LINE] + 1] = True
    return np.flatnonzero(first[:-1])


def _distinct(hashes: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of distinct values, and for each value which of them it is."""
    bits = max(4, int(len(hashes)).bit_length())
    slot, own = (hashes >> np.uint64(64 - bits)).astype(np.int64), np.arange(len(hashes))
    table = np.empty(1 << bits, np.int64)
    table[slot] = own
    like = table[slot]
    other = np.flatnonzero((hashes[like] != hashes) | (sizes[like] != sizes))
    _, place, inverse = np.unique(np.rec.fromarrays([hashes[other], sizes[other]]) if len(other) else hashes[:0], return_index=True, return_inverse=True)
    like[other] = other[place][inverse]
    kept = np.zeros(len(hashes), bool)
    kept[like] = True
    return np.flatnonzero(kept), (np.cumsum(kept) - 1)[like]


def columns(path: str) -> Callable[[Block], tuple[np.ndarray, np.ndarray]]:
    """A function from a block of texts to all their ids, as ``encoder`` gives them, and where each text's start, and the end."""
    ids, twin = encoder(path), path.removesuffix(".json") + ".tiktoken"
    if not (path.endswith("byte_bpe_50k.json") and os.path.exists(twin)):
        special = None
    else:
        (encoding, special), width = _byte_pairs(twin), _widths(twin)

    def plain(block: Block) -> tuple[np.ndarray, np.ndarray]:
        own = list(ids(block.text(i).decode() for i in range(len(block))))
        return np.concatenate([np.zeros(0, np.uint32), *own]), np.append(0, np.cumsum([len(x) for x in own]))

    def run(block: Block) -> tuple[np.ndarray, np.ndarray]:
        data, size = block.data, len(block.data)
        if special is None or not size:
            return plain(block)
        raw = data.tobytes()
        if any(s.encode() in raw for s in special):
            return plain(block)
        starts = _borders(block)
        ends = np.append(starts[1:], size)
        kept, which = _distinct(digests(data, starts, ends), ends - starts)
        a, b = starts[kept], ends[kept]
        # after each other they stay apart if they start with a space that a character follows and end with a character
        joined = (data[a] == _SPACE) & (b - a > 1) & _OPENS[data[np.minimum(a + 1, size - 1)]] & (_PLAIN[data[b - 1]] | (b - a > 2) & (data[b - 1] >= 0x80) & _TWO[data[b - 2]])
        found, n = [], np.zeros(len(kept), np.int64)
        sizes, ends_of = (b - a)[joined], np.cumsum((b - a)[joined])
        if len(sizes):
            text = data[np.arange(ends_of[-1]) + np.repeat(a[joined] - (ends_of - sizes), sizes)].tobytes().decode()
            found.append(encoding.encode_to_numpy(text, disallowed_special=()))
            at = np.cumsum(width[found[0]])
            last = np.searchsorted(at, ends_of)
            if not np.array_equal(at[np.minimum(last, len(at) - 1)], ends_of):
                return plain(block)
            n[joined] = np.diff(last, prepend=-1)
        for i in np.flatnonzero(~joined):
            found.append(encoding.encode_to_numpy(raw[a[i] : b[i]].decode(), disallowed_special=()))
            n[i] = len(found[-1])
        order = np.append(np.flatnonzero(joined), np.flatnonzero(~joined))
        first = np.empty(len(kept), np.int64)
        first[order] = np.cumsum(n[order]) - n[order]
        sizes = n[which]
        total = np.append(0, np.cumsum(sizes))
        every = np.concatenate(found)[np.arange(total[-1]) + np.repeat(first[which] - total[:-1], sizes)]
        return every, total[np.searchsorted(starts, block.offsets)]

    return run
