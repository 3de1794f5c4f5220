"""Packing of documents into windows of tokens, related documents next to each other.

1. Every text is cut into token ids once and written; document frequencies, the number of documents and
   their mean length are summed over the whole corpus, as many numbers as the vocabulary has tokens.
2. Documents are dealt to shards by what they share: the order is by the tokens of the greatest BM25
   weight in the document that enough others have to fill a shard, so documents with the same leading
   tokens, near copies above all, are neighbours.  One exchange by ranges of that order, and a shard is
   the next ``SHARD_TOKENS`` tokens of a range.
3. A shard has an inverted index with the corpus's statistics.  Each window starts with a seed; of the
   shard's unused documents the one nearest to the seed by BM25 follows, again and again, until the
   window is full.  A document that does not fit is cut; what is left of it is the seed of the next
   window.  So only a shard's last window is padded.

A seed is held against all unused documents of its shard, with every token it has; scoring all seeds
against all documents of the corpus would grow with the square of the input.  Work and memory are
bounded by the shard, whatever the size of the corpus; a corpus of one shard is searched as a whole.
Where no unused document shares a token with the seed, the next one in order follows.  Weights are whole
multiples of 1 / ``UNIT``, so sums are exact in any order; of equal scores the next in order after the
seed comes first.

Odd input: a null text is empty; an empty text is its end token alone; a text larger than a shard is a
shard of its own or its last document; repeated rows are packed each; null ids are kept; an empty table
gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from .storage import written
from .textblocks import blocks
from .tokens import DEFAULT, columns, vocabulary_path

WINDOW = 1024
#: Tokens of a shard, its last document aside.
SHARD_TOKENS = 2 << 20
#: Bytes of text that are cut into tokens at once.
TEXT_BYTES = 4 << 20
#: Up to so many shards each has a task of its own, beyond that a task packs some of them in turn.
MANY_TASKS, SHARDS_OF_TASK = 4000, 64
K1, B = 1.2, 0.75
#: Scores are counted in units small enough to order documents and large enough for sums of 32 bits: a score is
#: under 50 times the mean length of documents, whatever the document's length.
UNIT = float(1 << 10)
#: Leading tokens that documents are ordered by.
LEADING = 3
#: Tokens in more than a share of 1 / ``DENSE`` of a shard's documents are scored as rows of a matrix.
DENSE = 12


@dataclass
class Bags:
    """The distinct tokens of some documents and how often each has them, one document after the other."""

    sizes: np.ndarray  # distinct tokens of each document
    lengths: np.ndarray  # all tokens of each document
    terms: np.ndarray
    tf: np.ndarray

    @classmethod
    def of(cls, documents: list[np.ndarray]) -> Bags:
        own = [np.unique(d, return_counts=True) for d in documents]
        return cls(np.array([len(t) for t, _ in own]), np.array([len(d) for d in documents]), *(np.concatenate(x).astype(np.int64) for x in zip(*own, strict=True)))

    @property
    def docs(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.sizes)), self.sizes)


@dataclass
class Statistics:
    """What BM25 needs to know of the whole corpus."""

    df: np.ndarray  # by token id
    n: int
    mean: float

    @classmethod
    def of(cls, documents: list[np.ndarray]) -> Statistics:
        bags = Bags.of(documents)
        return cls(np.bincount(bags.terms).astype(float), len(documents), float(bags.lengths.mean()))

    def weights(self, bags: Bags) -> np.ndarray:
        """The BM25 weight of each token in its document, as whole numbers."""
        idf = np.log1p((self.n - self.df + 0.5) / (self.df + 0.5))
        norm = K1 * (1 - B + B * bags.lengths / self.mean)
        return np.rint(UNIT * idf[bags.terms] * bags.tf * (K1 + 1) / (bags.tf + np.repeat(norm, bags.sizes)))

    def leading(self, bags: Bags, least: float) -> np.ndarray:
        """For each document the tokens of the greatest weights among those in ``least`` documents or more, -1 where there are no more."""
        weights = np.where(self.df[bags.terms] >= least, self.weights(bags), -1)
        out = np.full((len(bags.sizes), LEADING), -1, np.int32)
        starts = np.cumsum(bags.sizes) - bags.sizes
        for i in range(LEADING):
            most = np.maximum.reduceat(weights, starts) if len(starts) else weights
            place = np.flatnonzero((weights == np.repeat(most, bags.sizes)) & (weights >= 0))
            doc, first = np.unique(bags.docs[place], return_index=True)
            out[doc, i] = bags.terms[place[first]]
            weights[place[first]] = -1
        return out


def _ranges(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places of all ranges, one after the other."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - sizes), sizes)


class ShardIndex:
    """Inverted lists of a shard's documents; those used are taken out when they are a quarter of it."""

    def __init__(self, bags: Bags, statistics: Statistics):
        self.n = len(bags.sizes)
        held = np.flatnonzero(np.bincount(bags.terms, minlength=len(statistics.df)))
        self.size = len(held)
        number = np.zeros(len(statistics.df), np.int64)
        number[held] = np.arange(self.size)
        terms, docs = number[bags.terms], bags.docs
        weights = statistics.weights(bags)
        wanted = (statistics.df[bags.terms] > 1) & (weights > 0)  # others add nothing to the score of another document
        terms, docs, weights = terms[wanted], docs[wanted], weights[wanted]
        self.queries = np.split(terms, np.cumsum(np.bincount(docs, minlength=self.n))[:-1])
        order = np.argsort(terms, kind="stable")
        self._lists(terms[order], docs[order], weights[order], np.arange(self.n))

    def _lists(self, terms: np.ndarray, docs: np.ndarray, weights: np.ndarray, left: np.ndarray) -> None:
        """``docs`` are places in ``left``."""
        self.left = left
        df = np.bincount(terms, minlength=self.size)
        many = df > max(1, len(left) // DENSE)
        self.row = np.where(many, np.cumsum(many) - 1, -1)
        own = many[terms]
        self.dense = np.zeros((int(many.sum()), len(left)), np.int32)
        self.dense[self.row[terms[own]], docs[own]] = weights[own]
        self.terms, self.docs, self.weights = terms[~own], docs[~own], weights[~own]
        self.starts = np.append(0, np.cumsum(np.where(many, 0, df)))

    def _shrink(self, used: np.ndarray) -> None:
        row, doc = np.nonzero(self.dense)
        of_row = np.flatnonzero(self.row >= 0)
        terms = np.concatenate([self.terms, of_row[row]])
        docs, weights = np.concatenate([self.docs, doc]), np.concatenate([self.weights, self.dense[row, doc]])
        stays = ~used[self.left]
        keep = stays[docs]
        terms, docs, weights = terms[keep], (np.cumsum(stays) - 1)[docs[keep]], weights[keep]
        order = np.argsort(terms, kind="stable")
        self._lists(terms[order], docs[order], weights[order], self.left[stays])

    def scores(self, seed: int) -> np.ndarray:
        """Exact scores of the documents in ``left``."""
        terms = self.queries[seed]
        rows = self.row[terms]
        out = np.add.reduce(self.dense[rows[rows >= 0]], axis=0, dtype=np.int32)
        terms = terms[rows < 0]
        at = _ranges(self.starts[terms], self.starts[terms + 1] - self.starts[terms])
        if len(at):
            out += np.bincount(self.docs[at], weights=self.weights[at], minlength=len(self.left)).astype(np.int32)
        return out

    def nearest(self, seed: int, used: np.ndarray, unused: int, k: int) -> tuple[np.ndarray, bool]:
        """The ``k`` nearest unused documents that share a token, nearest first, and whether there are more."""
        if 4 * unused < 3 * len(self.left):
            self._shrink(used)
        turn = 1 << max(1, int(self.n).bit_length())  # beyond all places
        scores = self.scores(seed)
        found = np.flatnonzero((scores > 0) & ~used[self.left])
        docs = self.left[found]
        keys = scores[found].astype(np.int64) * turn + (turn - 1 - ((docs - seed) & (turn - 1)))
        cut = len(keys) > k
        if cut:
            some = np.argpartition(keys, len(keys) - k)[-k:]
            keys, docs = keys[some], docs[some]
        return docs[np.argsort(-keys, kind="stable")], cut


def pack_shard(bags: Bags, window: int, statistics: Statistics, k: int = 64) -> list[tuple[int, int, int, int, int]]:
    """Pieces (document, start, length, window, offset) of the documents of a shard.

    A list of ``k`` nearest documents is asked for again when it is at its end and the window is not full.
    """
    n, sizes = len(bags.lengths), bags.lengths.tolist()
    index = ShardIndex(bags, statistics)
    used, unused, later = np.zeros(n, bool), n, 0
    pieces: list[tuple[int, int, int, int, int]] = []
    seed, number, fill = -1, 0, 0
    near, at, cut = np.zeros(0, np.int64), 0, False
    while unused:
        doc = -1
        if fill:
            while at < len(near) and used[near[at]]:
                at += 1
            if at == len(near) and cut:
                near, cut = index.nearest(seed, used, unused, k)
                at = 0
            if at < len(near):
                doc = int(near[at])
        if doc < 0:
            while used[later]:
                later += 1
            doc = later
        used[doc] = True
        unused -= 1
        size, start = sizes[doc], 0
        new = not fill  # an empty window: this document is its seed
        while start < size:
            take = min(window - fill, size - start)
            pieces.append((doc, start, take, number, fill))
            start, fill = start + take, fill + take
            if fill == window:
                number, fill = number + 1, 0
                new = start < size  # what is left of this document leads the next window
        if new:
            seed, at = doc, 0
            near, cut = np.zeros(0, np.int64), True
    return pieces


def _narrow(values: np.ndarray, offsets: np.ndarray) -> pa.Array:
    """The numbers of each document, two bytes each where all fit, after a byte that says so."""
    width = 2 if values.max(initial=0) < 1 << 16 else 4
    ends = offsets * width + np.arange(len(offsets))
    if ends[-1] >= 1 << 31:  # more than such an array holds
        return pa.array([bytes([width]) + values[a:b].astype(f"<u{width}").tobytes() for a, b in zip(offsets[:-1], offsets[1:])], pa.binary())
    data, rest = np.empty(ends[-1], np.uint8), np.ones(ends[-1], bool)
    data[ends[:-1]], rest[ends[:-1]] = width, False
    data[rest] = values.astype(f"<u{width}").view(np.uint8)
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(data)])


def _wide(ids) -> np.ndarray:
    ids = ids.as_buffer()
    return np.frombuffer(ids, f"<u{ids[0]}", offset=1)


#: A row for each document; the last rows of a task have no ids, but the task's documents by token.
TOKENS = "doc_id {}, digest long, size long, ids binary, terms binary, tf binary"


def _tokens(vocabulary: str, end: int, kind: pa.DataType):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, df = columns(vocabulary), np.zeros(1 << 16, np.int64)
        for batch in batches:
            for block in blocks(batch.column("text"), TEXT_BYTES):
                own, offsets = ids(block)
                n = len(block)
                size, offsets = np.diff(offsets) + 1, offsets + np.arange(n + 1)
                owner = np.repeat(np.arange(n), size)
                every = np.full(offsets[-1], end, np.uint32)
                every[np.arange(len(own)) + np.repeat(np.arange(n), size - 1)] = own
                # the distinct ids of each document and how often it has them
                turn = int(every.max()) + 1
                pairs = np.sort(owner * turn + every)
                first = np.flatnonzero(np.append(True, pairs[1:] != pairs[:-1]))
                tf = np.diff(np.append(first, len(pairs)))
                document, terms = np.divmod(pairs[first], turn)
                if turn > len(df):
                    df = np.append(df, np.zeros(turn, np.int64))
                df += np.bincount(terms, minlength=len(df))
                held = np.searchsorted(document, np.arange(n + 1))
                known = [batch.column(c).slice(block.first, n) for c in ("doc_id", "digest")]
                yield pa.RecordBatch.from_arrays([*known, pa.array(size), _narrow(every, offsets), _narrow(terms, held), _narrow(tf, held)], names=["doc_id", "digest", "size", "ids", "terms", "tf"])
        terms = np.flatnonzero(df)
        if len(terms):
            counted = [pa.nulls(1, kind), *(pa.array([x], k) for x, k in ((None, pa.int64()), (None, pa.int64()), (None, pa.binary()), (terms.tobytes(), pa.binary()), (df[terms].tobytes(), pa.binary())))]
            yield pa.RecordBatch.from_arrays(counted, names=["doc_id", "digest", "size", "ids", "terms", "tf"])

    return run


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for terms, n in zip(batch.column("terms"), batch.column("tf"), strict=True):
            yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(x.as_buffer(), np.int64)) for x in (terms, n)], names=["token", "df"])


def corpus_statistics(tokens: DataFrame) -> Statistics:
    """Sums of what the tasks have counted; a row a token of the vocabulary comes to the driver."""
    n, total = tokens.agg(F.count("size"), F.sum("size")).first()
    found = tokens.where("size is null").select("terms", "tf").mapInArrow(_frequencies, "token long, df long").groupBy("token").agg(F.sum("df").alias("df")).toArrow()
    token = found["token"].to_numpy()
    df = np.zeros(int(token.max()) + 1 if n else 1)
    df[token] = found["df"].to_numpy()
    return Statistics(df, n, (total or 0) / max(1, n))


def _bags(lengths: np.ndarray, terms: list, tf: list) -> Bags:
    terms, tf = [_wide(x) for x in terms], [_wide(x) for x in tf]
    return Bags(np.array([len(t) for t in terms], np.int64), lengths, np.concatenate(terms).astype(np.int64), np.concatenate(tf).astype(np.int64))


#: Keys a border between tasks that are told the driver.
KEYS_OF_BORDER = 20


def _order(batch: pa.RecordBatch, statistics: Statistics, least: float) -> np.ndarray:
    """The place of each document in the order of leading tokens, then digests, as byte strings."""
    leading = statistics.leading(_bags(batch.column("size").to_numpy(), batch.column("terms"), batch.column("tf")), least)
    out = np.empty(len(batch), [("leading", ">u4", LEADING), ("digest", ">u8"), ("row", ">u8")])
    out["leading"], out["digest"], out["row"] = leading + 1, batch.column("digest").to_numpy().view(np.uint64) ^ np.uint64(1 << 63), batch.column("row").to_numpy()
    return out.view(f"S{out.itemsize}")


def _some_keys(shared, least: float, step: float):
    """Of each batch, a key about every ``step`` tokens."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if len(batch):
                keys = _order(batch, shared.value, least)
                order = np.argsort(keys, kind="stable")
                at = (np.cumsum(batch.column("size").to_numpy()[order]) + step / 2) // step
                told = keys[order][np.flatnonzero(np.diff(at, prepend=0.0))]
                yield pa.RecordBatch.from_arrays([pa.array([x.ljust(keys.itemsize, b"\0") for x in told.tolist()], pa.binary())], names=["key"])

    return run


def _route(shared, least: float):
    """The task that each document goes to, and its key in the order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        statistics, borders = shared.value
        for batch in batches:
            if len(batch):
                keys = _order(batch, statistics, least)
                part = np.searchsorted(borders, keys, "right")
                whole = pa.FixedSizeBinaryArray.from_buffers(pa.binary(keys.itemsize), len(keys), [None, pa.py_buffer(keys.tobytes())]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([*batch.columns, whole, pa.array(part.astype(np.int32))], names=[*batch.schema.names, "key", "part"])

    return run


def _pack(shared, window: int, shard_tokens: int):
    """Packs a task's rows, a shard after the other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (statistics, _), first = shared.value, TaskContext.get().partitionId() << 32
        held: list[pa.RecordBatch] = []

        def packed(number: int) -> pa.RecordBatch:
            rows = pa.Table.from_batches(held).combine_chunks()
            sizes = rows["size"].to_numpy()
            pieces = np.array(pack_shard(_bags(sizes, rows["terms"], rows["tf"]), window, statistics), np.int64).reshape(-1, 5)
            doc, start, length, sequence, offset = pieces.T
            documents = [_wide(x) for x in rows["ids"]]
            cut = [documents[d][s : s + n].astype("<u4").tobytes() for d, s, n in zip(doc.tolist(), start.tolist(), length.tolist(), strict=True)]
            columns = [rows["doc_id"].combine_chunks().take(pa.array(doc)), *(pa.array(x) for x in (start, length, sizes[doc], first + number + sequence, offset)), pa.array(cut, pa.binary())]
            return pa.RecordBatch.from_arrays(columns, names=["doc_id", "start", "length", "doc_tokens", "sequence_id", "offset", "ids"])

        number, size = 0, 0
        for batch in batches:
            # a shard ends with the document that fills it
            ends = size + np.cumsum(batch.column("size").to_numpy())
            at = 0
            while at < len(batch):
                to = min(len(batch), int(np.searchsorted(ends, shard_tokens)) + 1)
                held.append(batch.slice(at, to - at))
                size = int(ends[to - 1])
                if size >= shard_tokens:
                    yield (out := packed(number))
                    number = int(out.column("sequence_id")[len(out) - 1].as_py()) - first + 1
                    ends, held, size = ends - size, [], 0
                at = to
        if held:
            yield packed(number)

    return run


def pack(docs: DataFrame, window: int = WINDOW, vocabulary: str | None = None, end: int = 0, shard_tokens: int = SHARD_TOKENS, id: str = "doc_id", text: str = "text") -> DataFrame:
    """A row for each piece: doc_id, start, length, doc_tokens, sequence_id, offset, ids (unsigned, 4 bytes each)."""
    spark = docs.sparkSession
    source = docs.select(F.col(id).alias("doc_id"), F.col(text).alias("text"))
    kind = dict(source.dtypes)["doc_id"]
    schema = TOKENS.format(kind)
    arrow = to_arrow_schema(source.select("doc_id").schema).field("doc_id").type
    tokens = source.withColumn("digest", F.xxhash64("doc_id", "text")).mapInArrow(_tokens(vocabulary or vocabulary_path(DEFAULT), end, arrow), schema)
    tokens = written(tokens.withColumn("row", F.monotonically_increasing_id()), "tokens")
    statistics = corpus_statistics(tokens)
    total = statistics.mean * statistics.n
    shards = max(1, -(-int(total) // shard_tokens))
    tasks = shards if shards <= MANY_TASKS else max(MANY_TASKS, shards // SHARDS_OF_TASK)
    least, known = max(2.0, statistics.n / shards), tokens.where("size is not null")
    shared = spark.sparkContext.broadcast(statistics)
    told = known.select("digest", "size", "terms", "tf", "row").mapInArrow(_some_keys(shared, least, max(1.0, total / (KEYS_OF_BORDER * tasks))), "key binary")
    keys = np.array(sorted(x["key"] for x in told.collect()) if tasks > 1 else [], f"S{4 * LEADING + 16}")
    borders = keys[[len(keys) * i // tasks for i in range(1, tasks)]] if len(keys) else keys
    both = spark.sparkContext.broadcast((statistics, borders))
    routed = known.select("doc_id", "digest", "size", "ids", "terms", "tf", "row").mapInArrow(_route(both, least), f"{schema}, row long, key binary, part int")
    dealt = routed.repartitionById(tasks, "part").sortWithinPartitions("key")
    schema = f"doc_id {kind}, start long, length long, doc_tokens long, sequence_id long, offset long, ids binary"
    return dealt.select("doc_id", "size", "ids", "terms", "tf").mapInArrow(_pack(both, window, shard_tokens), schema).withColumnRenamed("doc_id", id)


def op2(docs: DataFrame) -> DataFrame:
    return pack(docs).select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")
