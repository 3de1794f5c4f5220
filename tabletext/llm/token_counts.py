"""Token counts through a cache of content digests.

A text's key is the digest of its UTF-8 bytes (a null is an empty text: no other normalisation leaves
token counts as they are) together with the digest of the vocabulary file.  Known keys are joined to
stored counts; each distinct key that is not known is encoded once and appended to the cache.

Digests with a large share of the rows (``skew.py``) get their counts by broadcast, all others by a join.

The cache is a Parquet table that only grows.  Appending the same key twice (two runs at once, a task
that ran twice) does no harm: equal keys have equal counts and reads take one of them.

Odd input: null and empty texts have 0 bytes and 0 tokens; repeated rows stay rows; an empty table
gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .skew import heavy_keys
from .storage import shared_folder, written
from .tokens import DEFAULT, encoder, version, vocabulary_path

CACHE_SCHEMA = "digest binary, tokenizer string, n_tokens long"


def cache_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/tabletext/token-cache-{hashlib.md5(name.encode()).hexdigest()}"


def _exists(spark: SparkSession, path: str) -> bool:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def read_cache(spark: SparkSession, path: str) -> DataFrame:
    if not _exists(spark, path):
        return spark.createDataFrame([], CACHE_SCHEMA)
    return spark.read.schema(CACHE_SCHEMA).parquet(path)


def _encode(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = encoder(path)
        for batch in batches:
            texts = batch.column("text")
            counts = np.fromiter((len(x) for x in ids(t.as_py() for t in texts)), np.int64, len(texts))
            yield pa.RecordBatch.from_arrays([batch.column("digest"), pa.array(counts)], names=["digest", "n_tokens"])

    return run


def digest(text) -> F.Column:
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256))


def _distinct_in_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Drops repetitions inside a batch, so that a hot text leaves a task a few times at most."""
    for batch in batches:
        seen, keep = set(), []
        for i, d in enumerate(batch.column("digest")):
            if (d := d.as_py()) not in seen:
                seen.add(d)
                keep.append(i)
        yield batch.take(pa.array(keep, pa.int64()))


def missing_texts(docs: DataFrame, known: DataFrame, text: str = "text") -> DataFrame:
    """Each distinct text whose digest the cache has no count for.

    Texts move once, dealt by digest; the comparison with the cache and the choice of one row for each
    digest both happen where they arrive.
    """
    texts = docs.select(digest(F.col(text)).alias("digest"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    texts = texts.mapInArrow(_distinct_in_task, texts.schema)
    return texts.join(known.select("digest"), "digest", "left_anti").dropDuplicates(["digest"])


def update_cache(docs: DataFrame, path: str, vocabulary: str, text: str = "text") -> None:
    spark = docs.sparkSession
    tokenizer = version(vocabulary)
    known = read_cache(spark, path).where(F.col("tokenizer") == tokenizer)
    misses = missing_texts(docs, known, text).mapInArrow(_encode(vocabulary), "digest binary, n_tokens long")
    misses.select("digest", F.lit(tokenizer).alias("tokenizer"), "n_tokens").write.mode("append").parquet(path)


def token_counts(docs: DataFrame, path: str | None = None, vocabulary: str | None = None, limit: int = 1024, id: str = "doc_id", text: str = "text") -> DataFrame:
    """A row for each document: id, n_bytes, n_tokens, over_limit.  Brings the cache up to date first."""
    spark = docs.sparkSession
    vocabulary = vocabulary or vocabulary_path(DEFAULT)
    path = path or cache_path(spark, "default")
    update_cache(docs, path, vocabulary, text)
    keyed = docs.select(F.col(id), digest(F.col(text)).alias("digest"), F.coalesce(F.octet_length(F.col(text)), F.lit(0)).cast("long").alias("n_bytes"))
    keyed = written(keyed, "digests")
    heavy = written(heavy_keys(keyed, "digest", keyed.count()), "heavy-digests")
    # the cache has counts of all runs there were: only those asked for are grouped
    cache = read_cache(spark, path).where(F.col("tokenizer") == version(vocabulary)).select("digest", "n_tokens")
    one = lambda counts: counts.groupBy("digest").agg(F.first("n_tokens").alias("n_tokens"))
    few = one(cache.join(F.broadcast(heavy), "digest", "left_semi"))
    light = keyed.join(F.broadcast(heavy), "digest", "left_anti")
    rest = light.join(one(cache.join(light.select("digest"), "digest", "left_semi")), "digest", "left")
    both = keyed.join(F.broadcast(few), "digest").unionByName(rest)
    return both.select(id, "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
