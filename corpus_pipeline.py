"""A corpus from documents to packed windows, one operator of ``tabletext.llm`` a stage."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from tabletext.llm import decontamination, language, near_duplicates, packing, suffix_dedup
from tabletext.llm.storage import mark, release, shared_folder
from tabletext.sources.tables import spread
from tabletext.storage import delete
from tabletext.shipping import ship


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the languages learned; those without a letter, or like none of them, go."""
    ship(spark)
    return language.keep_identified(docs, language.train(docs))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: five words a shingle, similarity 0.8 or more."""
    ship(spark)
    return near_duplicates.drop_near_duplicates(docs, words=5, threshold=0.8)


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of 200 bytes that occur elsewhere too."""
    ship(spark)
    return suffix_dedup.remove_repeats(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no window of a benchmark item."""
    ship(spark)
    return decontamination.decontaminate(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in windows of 1024 tokens."""
    ship(spark)
    return packing.op2(docs)


STAGES = [
    ("language ID", language_id),
    ("MinHash near-dedup", near_dedup),
    ("suffix-array dedup", suffix_array_dedup),
    ("benchmark decontamination", benchmark_decontamination),
    ("packing", pack_windows),
]

#: Models, suffix arrays and token ids are beyond SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn, each written and read again as the next one's documents.

    When a stage is written, its intermediate tables and the stage before it are deleted.
    """
    docs = spread(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    folder = f"{shared_folder(spark)}/tabletext/pipeline-{uuid.uuid4().hex}"
    for i, (_, stage) in enumerate(STAGES):
        before = mark()
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{folder}/{i}")
        release(spark, before)
        if i:
            delete(spark, f"{folder}/{i - 1}")
        docs = spark.read.schema(out.schema).parquet(f"{folder}/{i}")
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {"pipeline": ORACLE_SQL} if ORACLE_SQL else {}
