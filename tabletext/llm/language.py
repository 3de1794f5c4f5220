"""Language identification by prediction by partial matching.

For each language a tree of byte contexts up to ``ORDER`` bytes holds how often each byte followed.
The code length of a byte is that of its probability in the longest context known to the language;
each escape to a shorter context adds its own code length (method C: the number of distinct bytes
seen in the context, over that number plus all it has seen); below the empty context all 256 bytes
are equally likely.  Statistics are frozen after training, so a text's code length is a sum over its
positions of a function of ``ORDER + 1`` bytes, and the language with the least sum wins.

That function is evaluated exactly, once for each distinct run of bytes that a worker meets, and
then looked up: by the numbers of its two pairs of bytes in a square table.

Training reads a sample of at most ``TRAIN_BYTES`` of text a language: rows in the order of a digest of
id and text until that many bytes are full, the last one cut, so every language has at least the
beginning of one text.  Everything else covers all rows and whole texts.

Odd input: null texts and texts without a letter are ``und`` with score 0; without any training row
all others are ``und`` as well; ties go to the language first in the alphabet; repeated rows are each
answered; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .textblocks import blocks

ORDER = 3
TRAIN_BYTES = 600_000
#: Code length in bits a byte beyond which a text is in none of the languages; noise needs 8 and more,
#: texts of a known language under 4.
MAX_BITS = 6.5
UNKNOWN = "und"
#: Bytes of code lengths that a worker keeps.
TABLE_BYTES = 128 << 20


def _codes(data: np.ndarray, length: int) -> np.ndarray:
    """The code of the ``length`` bytes that end at each position from ``length - 1`` on."""
    out = np.zeros(max(0, len(data) - length + 1), dtype=np.uint32)
    for i in range(length):
        out = (out << np.uint32(8)) | data[i : i + len(out)]
    return out


@dataclass
class ContextTree:
    """Counts by order: sorted codes of context and byte, and of contexts with their totals."""

    grams: list[np.ndarray]
    counts: list[np.ndarray]
    contexts: list[np.ndarray]
    totals: list[np.ndarray]
    kinds: list[np.ndarray]

    @classmethod
    def learn(cls, texts: list[bytes]) -> ContextTree:
        """Each text starts in the context of ``ORDER`` zero bytes."""
        parts = [np.frombuffer(bytes(ORDER) + t, dtype=np.uint8) for t in texts if t]
        out = cls([], [], [], [], [])
        for order in range(ORDER + 1):
            codes = [_codes(p[ORDER - order :], order + 1) for p in parts]
            gram, count = np.unique(np.concatenate(codes) if codes else np.zeros(0, np.uint32), return_counts=True)
            context, first, kinds = np.unique(gram >> np.uint32(8), return_index=True, return_counts=True)
            out.grams.append(gram)
            out.counts.append(count)
            out.contexts.append(context)
            out.totals.append(np.add.reduceat(count, first) if len(first) else count)
            out.kinds.append(kinds)
        return out

    def bits(self, codes: np.ndarray) -> np.ndarray:
        """Exact code length of the last byte of each code after the bytes before it."""
        bits = np.zeros(len(codes))
        open_ = np.ones(len(codes), dtype=bool)
        for order in range(ORDER, -1, -1):
            wide = np.uint32(0xFFFFFFFF >> (8 * (ORDER - order)))
            gram = codes & wide
            context = gram >> np.uint32(8)
            at, known = _find(self.contexts[order], context)
            seen, has = _find(self.grams[order], gram)
            here = open_ & known
            if not len(self.contexts[order]):
                continue
            whole = (self.totals[order] + self.kinds[order])[at]
            hit = here & has
            bits[hit] += np.log2(whole[hit] / self.counts[order][seen[hit]])
            miss = here & ~has
            bits[miss] += np.log2(whole[miss] / self.kinds[order][at[miss]])
            open_ &= ~hit
        bits[open_] += 8.0
        return bits


def _find(values: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(values):
        return np.zeros(len(x), np.int64), np.zeros(len(x), bool)
    at = np.minimum(np.searchsorted(values, x), len(values) - 1)
    return at, values[at] == x


@dataclass
class Model:
    languages: list[str]
    trees: list[ContextTree]

    def bits(self, codes: np.ndarray) -> np.ndarray:
        return np.stack([t.bits(codes) for t in self.trees], axis=1).astype(np.float64)


class Scorer:
    """Code lengths of whole texts, with what it has met kept in a table of bounded size."""

    PAIRS = 4096

    def __init__(self, model: Model):
        self.model = model
        self.number = np.full(1 << 16, -1, dtype=np.int32)  # pair of bytes -> its number
        self.pairs = 0
        self.square = np.full(self.PAIRS * self.PAIRS, -1, dtype=np.int32)
        self.costs = np.zeros((1024, len(model.languages)))
        self.used = 0

    def _rows(self, codes: np.ndarray) -> np.ndarray:
        """For each code the row of ``costs`` that has its code lengths; new codes are evaluated."""
        high, low = codes >> np.uint32(16), codes & np.uint32(0xFFFF)
        for pair in (high, low):
            new = np.flatnonzero(np.bincount(pair[self.number[pair] < 0], minlength=1)) if (self.number[pair] < 0).any() else []
            for p in new:
                if self.pairs < self.PAIRS:
                    self.number[p] = self.pairs
                    self.pairs += 1
        a, b = self.number[high], self.number[low]
        at = a.astype(np.int64) * self.PAIRS + b
        at[(a < 0) | (b < 0)] = -1
        row = np.where(at >= 0, self.square[at], -1)
        missing = np.flatnonzero(row < 0)
        if len(missing):
            fresh, first, back = np.unique(codes[missing], return_index=True, return_inverse=True)
            need = self.used + len(fresh)
            if need > len(self.costs):
                self.costs = np.concatenate([self.costs, np.zeros((max(need, 2 * len(self.costs)) - len(self.costs), self.costs.shape[1]))])
            self.costs[self.used : need] = self.model.bits(fresh)
            row[missing] = self.used + back
            kept = at[missing[first]]
            self.square[kept[kept >= 0]] = (self.used + np.arange(len(fresh)))[kept >= 0]
            self.used = need
        return row

    def block(self, block) -> np.ndarray:
        """Bits of each text in each language."""
        n, lengths = len(block), np.diff(block.offsets)
        starts = block.offsets[:-1] + ORDER * np.arange(1, n + 1)
        data = np.zeros(len(block.data) + ORDER * n, dtype=np.uint8)
        place = np.repeat(starts - block.offsets[:-1], lengths) + np.arange(len(block.data))
        data[place] = block.data
        if self.used * self.costs.shape[1] * 8 > TABLE_BYTES:  # codes beyond the pairs that have numbers gather: start again
            self.__init__(self.model)
        rows = self._rows(_codes(data, ORDER + 1)[place - ORDER]) if len(place) else np.zeros(0, np.int64)
        costs = self.costs[rows]
        sums = np.zeros((n, costs.shape[1]))
        full = np.flatnonzero(lengths)
        if len(full):
            sums[full] = np.add.reduceat(costs, block.offsets[:-1][full], axis=0)
        return sums


#: Rows that a language's sample is chosen from hold so many times its bytes, as expected.
SPARE = 4


def training_sample(rows: DataFrame, language: str = "lang", text: str = "text", id: str = "doc_id", train_bytes: int = TRAIN_BYTES) -> DataFrame:
    """lang, place, text (bytes): the sample of each language, at most ``train_bytes`` each.

    A share of the rows that is expected to hold ``SPARE`` times the sample is sorted, and so is the row of
    the least digest, whatever its size: no language is lost, and no sort grows with the input.
    """
    known = rows.where(F.col(language).isNotNull() & F.col(text).isNotNull() & (F.octet_length(text) > 0))
    known = known.select(F.col(language).cast("string").alias("lang"), F.col(text).cast("binary").alias("text"), F.md5(F.concat_ws(" ", F.col(id).cast("string"), F.md5(F.col(text).cast("binary")))).alias("key"))
    sizes = known.groupBy("lang").agg(F.sum(F.octet_length("text")).alias("bytes"), F.min("key").alias("least"))
    share = F.conv(F.substring("key", 1, 12), 16, 10).cast("double") / F.lit(float(1 << 48))
    near = known.join(F.broadcast(sizes), "lang").where((F.col("key") == F.col("least")) | (share < F.lit(float(SPARE * train_bytes)) / F.col("bytes")))
    cut = near.select("lang", "key", F.substring("text", 1, train_bytes).alias("text"))
    own = W.partitionBy("lang").orderBy("key", "text")
    placed = cut.withColumn("place", F.row_number().over(own)).withColumn("before", F.sum(F.octet_length("text")).over(own.rowsBetween(W.unboundedPreceding, -1)))
    room = F.lit(train_bytes) - F.coalesce("before", F.lit(0))
    return placed.where(room > 0).select("lang", "place", F.expr("text").substr(F.lit(1), room.cast("int")).alias("text"))


def train(rows: DataFrame, language: str = "lang", text: str = "text", id: str = "doc_id", train_bytes: int = TRAIN_BYTES) -> Model:
    """A context tree for each language; at most ``train_bytes`` a language come to the driver."""
    texts: dict[str, list[bytes]] = {}
    for r in training_sample(rows, language, text, id, train_bytes).orderBy("lang", "place").collect():
        texts.setdefault(r["lang"], []).append(bytes(r["text"]))
    languages = sorted(texts)
    return Model(languages, [ContextTree.learn(texts[x]) for x in languages])


def identify(docs: DataFrame, model: Model, id: str = "doc_id", text: str = "text") -> DataFrame:
    """id, lang_pred, score, bits_per_byte (in the language predicted) of each document."""
    source = docs.select(F.col(id).alias("id"), F.col(text).alias("text"), F.coalesce(F.col(text).rlike(r"\p{L}"), F.lit(False)).alias("letters"))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value) if shared.value.languages else None
        names = [*shared.value.languages, UNKNOWN]
        for batch in batches:
            letters = batch.column("letters").to_numpy(zero_copy_only=False).astype(bool)
            best, score, rate = np.full(len(batch), len(names) - 1), np.zeros(len(batch)), np.zeros(len(batch))
            for block in blocks(batch.column("text")) if scorer else ():
                bits = scorer.block(block)
                least = bits.argmin(axis=1)
                lead = np.exp2(np.clip(bits.min(axis=1)[:, None] - bits, -1000, 0))
                at = slice(block.first, block.first + len(block))
                best[at], score[at] = least, 1 / lead.sum(axis=1)
                rate[at] = bits.min(axis=1) / np.maximum(1, np.diff(block.offsets))
            best[~letters], score[~letters] = len(names) - 1, 0.0
            out = [batch.column("id"), pa.array(np.array(names, dtype=object)[best].tolist(), pa.string()), pa.array(score), pa.array(rate)]
            yield pa.RecordBatch.from_arrays(out, names=["id", "lang_pred", "score", "bits_per_byte"])

    kinds = dict(source.dtypes)
    schema = f"id {kinds['id']}, lang_pred string, score double, bits_per_byte double"
    return source.mapInArrow(run, schema).withColumnRenamed("id", id)


def keep_identified(docs: DataFrame, model: Model, max_bits: float = MAX_BITS, text: str = "text") -> DataFrame:
    """Documents with a letter whose best language needs at most ``max_bits`` a byte; columns as they were."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value) if shared.value.languages else None
        for batch in batches:
            keep = np.zeros(len(batch), bool)
            for block in blocks(batch.column(text)) if scorer else ():
                rate = scorer.block(block).min(axis=1) / np.maximum(1, np.diff(block.offsets))
                keep[block.first : block.first + len(block)] = rate <= max_bits
            yield batch.filter(pa.array(keep))

    return docs.where(F.col(text).rlike(r"\p{L}")).mapInArrow(run, docs.schema)


def remainder(id):
    """The checksum of the id, written as text, modulo 4."""
    return F.pmod(F.crc32(id.cast("string").cast("binary")), F.lit(4))


def op5(docs: DataFrame) -> DataFrame:
    held_out = F.coalesce(remainder(F.col("doc_id")) == 2, F.lit(False))
    model = train(docs.where(~held_out))
    return identify(docs.select("doc_id", "text"), model).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")
