"""Near-duplicate detection by MinHash bands, checked on full sets, with exact components.

1. A pass over the texts gives each document its shingle count, a digest of its shingle set, the
   minima of ``BANDS * ROWS`` universal hashes and a hash of each band of them.
2. Documents with equal sets are one class; only classes go on, so groups of copies cost one row.
3. In each bucket (classes with one band in common) all classes are paired with its centre: the one
   whose buckets hold most classes.  In a family of near copies that is the text they come from.
   Pairs are tested on their signatures, then on their full sets.
4. Components of the links found so far come from alternating large-star and small-star.
5. A bucket whose classes are all in one component is settled: links inside it change nothing.
   In the others, classes of different components meet in blocks of bounded size, which hold the full
   sets.  A block tests a pair in the first band that both share, skips pairs that are joined already,
   and reports a link only where it joins components; so no link that a bucket can show is lost, and
   no block reports more links than it has classes.

A pair at similarity 0.8 shares no bucket with a probability of (1 - 0.8 ** 4) ** 32, about 5e-8.
The signature test drops a pair below ``threshold - SLACK``, over five standard deviations off.

Odd input: null texts and texts without words have an empty set and link with nothing; repeated rows
are copies of each other; among equal least ids every row with it is kept; a null id is never the least
one of a component that has another, and is kept where all are null; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import written
from .textblocks import PLAIN_WORDS, Block, Words, blocks, digests, grams, mix

BANDS, ROWS = 32, 4
SLACK = 0.2
#: Ids of copies that may be sent to all tasks; with more of them both sides are dealt by id.
BROADCAST_IDS = 1_000_000
#: Classes of a bucket that are compared with as many others in one task.
BLOCK = 512

_random = np.random.default_rng(20240229)
#: Multiply-shift: the upper half of a * x + b modulo 2**64 over 32-bit x is strongly universal.
_FACTORS = _random.integers(0, 1 << 64, BANDS * ROWS, dtype=np.uint64)
_TERMS = _random.integers(0, 1 << 64, BANDS * ROWS, dtype=np.uint64)


def shingle_sets(block: Block, k: int) -> list[np.ndarray]:
    """The sorted distinct shingles of each text: k words, or all words of a text with fewer."""
    words = Words(block, PLAIN_WORDS, lower=True)
    shingles = grams(words.hashes, k)
    out = []
    for a, b in zip(words.offsets[:-1].tolist(), words.offsets[1:].tolist(), strict=True):
        if b - a >= k:
            own = np.sort(shingles[a : b - k + 1])
            out.append(own[np.append(True, own[1:] != own[:-1])])
        elif b > a:
            out.append(digests(words.hashes, np.array([a]), np.array([b])))
        else:
            out.append(shingles[:0])
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """The minima of all hashes over each set; none may be empty."""
    values = np.concatenate(sets) >> np.uint64(32)
    starts = np.cumsum([0] + [len(s) for s in sets[:-1]])
    out = np.empty((len(sets), BANDS * ROWS), dtype=np.uint32)
    hashed = np.empty_like(values)
    for j in range(BANDS * ROWS):
        np.multiply(values, _FACTORS[j], out=hashed)
        hashed += _TERMS[j]
        out[:, j] = np.minimum.reduceat(hashed, starts) >> np.uint64(32)
    return out


def bands(minima: np.ndarray) -> np.ndarray:
    parts = minima.reshape(len(minima), BANDS, ROWS).astype(np.uint64)
    code = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15), parts.shape[:2]).copy()
    for r in range(ROWS):
        code = mix(code ^ parts[:, :, r]) * np.uint64(0x9E3779B97F4A7C15)
    return mix(code)


SKETCH = "doc_id {}, n_shingles long, node long, bands array<long>, signature binary"


def _node(own: np.ndarray) -> int:
    return int.from_bytes(blake2b(own.tobytes(), digest_size=8).digest(), "little", signed=True)


def _sketch(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("text"), 1 << 20):
                sets = shingle_sets(block, k)
                full = [i for i, s in enumerate(sets) if len(s)]
                nodes, codes, minima = [None] * len(sets), [None] * len(sets), [None] * len(sets)
                if full:
                    rows = signatures([sets[i] for i in full])
                    keys = bands(rows).view(np.int64)
                    for n, i in enumerate(full):
                        nodes[i], codes[i], minima[i] = _node(sets[i]), keys[n], rows[n].tobytes()
                ids = batch.column("doc_id").slice(block.first, len(block))
                yield pa.RecordBatch.from_arrays(
                    [ids, pa.array([len(s) for s in sets], pa.int64()), pa.array(nodes, pa.int64()), pa.array(codes, pa.list_(pa.int64())), pa.array(minima, pa.binary())],
                    names=["doc_id", "n_shingles", "node", "bands", "signature"],
                )

    return run


def sketches(docs: DataFrame, k: int) -> DataFrame:
    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(_sketch(k), SKETCH.format(kind))


# --- components -----------------------------------------------------------------------------


def _star(edges: DataFrame, large: bool) -> DataFrame:
    both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))) if large else edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
    moved = both.join(least, "a")
    if large:
        out = moved.where(F.col("b") > F.col("a")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        out = moved.select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
    return out.where("a <> b").distinct()


def components(edges: DataFrame) -> DataFrame:
    """node, label: the least node of its component, for each node that has an edge."""

    def state(df: DataFrame):
        return df.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first()

    edges = written(edges.toDF("a", "b").where("a <> b").distinct(), "edges")
    before = state(edges)
    while before[0]:
        edges = written(_star(_star(edges, True), False), "edges")
        now = state(edges)
        if now == before:
            break
        before = now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("label")).union(edges.select("b", "b").distinct())


# --- verification ---------------------------------------------------------------------------


def _similar(least: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not len(batch):
                continue
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint32).reshape(len(batch), -1) for c in ("sa", "sb"))
            keep = (x == y).sum(axis=1) >= least
            yield pa.RecordBatch.from_arrays([batch.column(c).filter(pa.array(keep)) for c in ("a", "b")], names=["a", "b"])

    return run


def _similar_sets(x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
        return False
    both = np.sort(np.concatenate([x, y]))
    common = int((both[1:] == both[:-1]).sum())
    return 100 * common >= percent * (len(x) + len(y) - common)


def _linked(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pairs = zip(batch.column("xa"), batch.column("xb"), strict=True)
            keep = [_similar_sets(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), percent) for x, y in pairs]
            yield pa.RecordBatch.from_arrays([batch.column(c).filter(pa.array(keep, pa.bool_())) for c in ("a", "b")], names=["a", "b"])

    return run


def _full_sets(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("text")):
                wanted = batch.column("node").slice(block.first, len(block)).to_pylist()
                own = [(n, s) for n, s in zip(wanted, shingle_sets(block, k), strict=True) if len(s) and _node(s) == n]
                yield pa.RecordBatch.from_arrays([pa.array([n for n, _ in own], pa.int64()), pa.array([s.tobytes() for _, s in own], pa.binary())], names=["node", "shingles"])

    return run


def full_sets(nodes: DataFrame, classes: DataFrame, docs: DataFrame, k: int) -> DataFrame:
    """node, shingles of the classes asked for, from the text of one document each."""
    wanted = classes.select("node", F.col("first_id").alias("doc_id")).join(nodes, "node", "left_semi")
    texts = docs.select(F.col("doc_id").alias("id"), "text").join(wanted, F.col("id").eqNullSafe(F.col("doc_id"))).select("node", "text")
    return written(texts.mapInArrow(_full_sets(k), "node long, shingles binary").dropDuplicates(["node"]), "shingles")


def confirmed(pairs: DataFrame, classes: DataFrame, docs: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs whose full sets have the similarity asked for."""
    sets = full_sets(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct(), classes, docs, k)
    joined = pairs.join(sets.toDF("a", "xa"), "a").join(sets.toDF("b", "xb"), "b")
    return joined.mapInArrow(_linked(percent), "a long, b long")


class Forest:
    """Components of the classes of a block, by their labels."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        while (y := self.up.get(x, x)) != x:
            self.up[x] = self.up.get(y, y)
            x = y
        return x


def _candidates(pdf: pd.DataFrame, least: int):
    """Pairs (rows of the left, rows of the right side) to test in a pair of blocks: signatures near
    enough, components different, this band the first they share, and neither is the bucket's centre."""
    left, right = pdf[pdf["side"] == 0].reset_index(drop=True), pdf[pdf["side"] == 1].reset_index(drop=True)
    if not len(left) or not len(right):
        return left, right, []
    x, y = (np.frombuffer(b"".join(s["signature"]), np.uint32).reshape(len(s), BANDS * ROWS) for s in (left, right))
    band, centre = int(pdf["band"].iloc[0]), int(pdf["centre"].iloc[0])
    b, lb = right["node"].to_numpy(), right["label"].to_numpy()
    out = []
    for i, (node, label) in enumerate(zip(left["node"], left["label"], strict=True)):
        if node == centre:
            continue
        same = y == x[i]
        hit = np.flatnonzero((same.sum(axis=1) >= least) & (lb != label) & (b != centre))
        if len(hit):
            first = same[hit].reshape(len(hit), BANDS, ROWS).all(axis=2).argmax(axis=1)
            out.append((i, hit[first == band]))
    return left, right, out


def _nodes_to_test(least: int):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        left, right, found = _candidates(pdf, least)
        nodes = {int(left["node"][i]) for i, hit in found if len(hit)} | {int(n) for _, hit in found for n in right["node"].to_numpy()[hit]}
        return pd.DataFrame({"node": pd.Series(sorted(nodes), dtype="int64")})

    return run


def _joining_links(least: int, percent: int):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        left, right, found = _candidates(pdf, least)
        forest, links = Forest(), []
        sets = [[np.frombuffer(s, np.uint64) for s in side["shingles"]] for side in (left, right)]
        for i, hit in found:
            for j in hit.tolist():
                a, b = forest.root(int(left["label"][i])), forest.root(int(right["label"][j]))
                if a != b and _similar_sets(sets[0][i], sets[1][j], percent):
                    forest.up[max(a, b)] = min(a, b)
                    links.append((int(left["node"][i]), int(right["node"][j])))
        return pd.DataFrame(links, columns=["a", "b"], dtype="int64")

    return run


def _blocks(members: DataFrame, *content: str) -> DataFrame:
    """Members of mixed buckets, dealt to pairs of blocks: those outside a bucket's largest component
    (side 0) meet all others (side 1).  The largest component is not compared with itself."""
    by_label = members.groupBy("bucket", "label").agg(F.count("*").alias("n"))
    shape = by_label.groupBy("bucket").agg(F.max(F.struct("n", "label")).alias("top"), F.sum("n").alias("size"))
    shape = shape.select("bucket", F.col("top.label").alias("main"), F.ceil((F.col("size") - F.col("top.n")) / F.lit(BLOCK)).cast("int").alias("minor"), F.ceil(F.col("size") / F.lit(BLOCK)).cast("int").alias("all"))
    members = members.join(shape, "bucket")
    spot = F.xxhash64("node", "bucket")
    minor, every = F.pmod(spot, F.col("minor")).cast("int"), F.pmod(spot, F.col("all")).cast("int")
    same = ["band", "centre", "node", "label", *content]
    left = members.where("label <> main").select("bucket", minor.alias("i"), F.explode(F.sequence(F.lit(0), F.col("all") - 1)).alias("j"), F.lit(0).alias("side"), *same)
    right = members.select("bucket", F.explode(F.sequence(F.lit(0), F.col("minor") - 1)).alias("i"), every.alias("j"), F.lit(1).alias("side"), *same)
    return left.union(right)


def joining_links(buckets: DataFrame, labels: DataFrame, classes: DataFrame, docs: DataFrame, k: int, least: int, percent: int) -> DataFrame | None:
    """Links that join components in buckets of more than one; None if there are no such buckets."""
    tagged = buckets.join(labels, "node", "left").select("bucket", "band", "centre", "node", F.coalesce("label", "node").alias("label"))
    mixed = tagged.groupBy("bucket").agg(F.count("*").alias("size"), F.min("label").alias("x"), F.max("label").alias("y")).where("x <> y and size > 2")
    members = tagged.join(mixed.select("bucket"), "bucket", "left_semi")
    members = written(members.join(classes.select("node", "signature"), "node"), "mixed-buckets")
    nodes = _blocks(members, "signature").groupBy("bucket", "i", "j").applyInPandas(_nodes_to_test(least), "node long")
    nodes = written(nodes.distinct(), "nodes-to-test")
    if not nodes.limit(1).count():
        return None
    sets = full_sets(nodes, classes, docs, k)
    return _blocks(members.join(sets, "node"), "signature", "shingles").groupBy("bucket", "i", "j").applyInPandas(_joining_links(least, percent), "a long, b long")


def near_duplicate_classes(docs: DataFrame, words: int = 5, threshold: float = 0.8, id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, node (class of equal sets), component_id: a row for each document."""
    percent, least = round(100 * threshold), int((threshold - SLACK) * BANDS * ROWS)
    docs = docs.select(F.col(id).alias("doc_id"), F.col(text).alias("text"))
    sketch = written(sketches(docs, words), "sketches")
    classes = written(sketch.where("node is not null").groupBy("node").agg(F.min("doc_id").alias("first_id"), F.first("bands").alias("bands"), F.first("signature").alias("signature")), "classes")
    buckets = classes.select(F.posexplode("bands").alias("band", "bucket"), "node")
    shared = buckets.groupBy("bucket").agg(F.count("*").alias("size")).where("size > 1")
    buckets = written(buckets.join(shared, "bucket"), "buckets")
    weight = buckets.groupBy("node").agg(F.sum("size").alias("weight"))
    centre = buckets.join(weight, "node").groupBy("bucket").agg(F.max_by("node", F.struct("weight", "node")).alias("centre"))
    buckets = written(buckets.select("bucket", "band", "node").join(centre, "bucket"), "buckets")
    stars = written(buckets.where("centre <> node").select(F.col("centre").alias("a"), F.col("node").alias("b")).distinct(), "stars")

    signed = classes.select("node", "signature")
    near = stars.join(signed.toDF("a", "sa"), "a").join(signed.toDF("b", "sb"), "b").mapInArrow(_similar(least), "a long, b long")
    links = written(confirmed(written(near, "candidates"), classes, docs, words, percent), "links")
    labels = components(links)

    more = joining_links(buckets, labels, classes, docs, words, least, percent)
    if more is not None:
        labels = components(written(links.union(more), "links"))
    labels = written(labels, "labels")

    least_id = classes.select("node", "first_id").join(labels, "node").groupBy("label").agg(F.min("first_id").alias("component_id"))
    of = labels.join(least_id, "label").select("node", "component_id")
    ids = classes.select("node", "first_id").join(of, "node", "left").select("node", F.coalesce("component_id", "first_id").alias("component_id"))
    return sketch.select("doc_id", "n_shingles", "node").join(ids, "node", "left").select(
        F.col("doc_id").alias(id), "n_shingles", "node", F.coalesce("component_id", "doc_id").alias("component_id")
    )


def drop_near_duplicates(docs: DataFrame, words: int = 5, threshold: float = 0.8, id: str = "doc_id", text: str = "text") -> DataFrame:
    """One document of each component, that with the least id; columns as they were.

    Rows that repeat an id with other content stay if one of them is kept; a row with a null id stays.
    """
    found = near_duplicate_classes(docs, words, threshold, id, text)
    name = "__gone" + "_" * max(map(len, docs.columns))  # a name that no column has
    gone = written(found.where(F.col(id) != F.col("component_id")).select(F.col(id).alias(name)).distinct(), "copies")
    if gone.count() <= BROADCAST_IDS:  # then the texts stay where they are
        gone = F.broadcast(gone)
    return docs.join(gone, F.col(id) == F.col(name), "left_anti")


def op8(docs: DataFrame) -> DataFrame:
    found = near_duplicate_classes(docs, words=2)
    return found.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))
