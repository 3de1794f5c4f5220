"""Queries over the given tables, and their SQL where SQL can say it."""

from __future__ import annotations

import hashlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..shipping import ship
from ..sources.tables import spread
from . import decontamination, language, near_duplicates, oracles, packing, search, sharding, substring_dedup, suffix_dedup, token_counts, url_filter


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spread(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def op1_histogram_sort(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.op1(_table(spark, sf_dir, "documents"))


def op2_lexical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.op2(_table(spark, sf_dir, "documents"))


def op3_temporal_url_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.op3(_table(spark, sf_dir, "pages"))


def op4_block_max_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search.op4(_table(spark, sf_dir, "documents"))


def op5_partial_matching(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.op5(_table(spark, sf_dir, "documents"))


def op6_common_prefix_intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.op6(_table(spark, sf_dir, "documents"))


def op7_fm_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.op7(_table(spark, sf_dir, "documents"))


def op8_minhash_star_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.op8(_table(spark, sf_dir, "documents"))


def op9_digest_cache(spark: SparkSession, sf_dir: str) -> DataFrame:
    # a cache for each input folder: another run over the same folder encodes nothing
    return token_counts.token_counts(_table(spark, sf_dir, "documents"), token_counts.cache_path(spark, hashlib.md5(sf_dir.encode()).hexdigest()))


def op10_training_suffix_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.op10(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_histogram_sort, op2_lexical_packing, op3_temporal_url_lists, op4_block_max_search, op5_partial_matching, op6_common_prefix_intervals, op7_fm_index, op8_minhash_star_components, op9_digest_cache, op10_training_suffix_arrays)}


def oracle_sql() -> dict[str, str]:
    return dict(oracles.SQL)
