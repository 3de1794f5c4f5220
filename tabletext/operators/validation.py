"""Scores of reports against their own cells, all in the row: no join, no shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import fidelity, numeric, temporal
from . import judging

METRICS = ("numeric_p", "numeric_r", "temporal_p", "temporal_r")


def with_mentions(reports: DataFrame) -> DataFrame:
    return reports.withColumn("dates", temporal.parse_dates(F.col("text"))).withColumn("numbers", numeric.parse_numbers(F.col("text")))


def numeric_fidelity(text: Column, cells: Column, mode: str = "bag") -> Column:
    return fidelity.match_numbers(numeric.truth_numbers(cells), numeric.values(numeric.parse_numbers(text)), mode)


def temporal_fidelity(text: Column, cells: Column, mode: str = "bag") -> Column:
    return fidelity.match_dates(temporal.truth_dates(cells), temporal.values(temporal.parse_dates(text)), mode)


def _scored(out: DataFrame, keys: list[str], made: list[Column]) -> DataFrame:
    numbers = fidelity.match_numbers(numeric.truth_numbers(F.col("cells")), numeric.values(F.col("numbers")))
    dates = fidelity.match_dates(temporal.truth_dates(F.col("cells")), temporal.values(F.col("dates")))
    out = out.select(*keys, numbers.alias("numeric"), dates.alias("temporal"), *made)
    return out.select("*", *(F.col(f"{k}.{m}").alias(f"{k}_{m}") for k in ("numeric", "temporal") for m in ("tp", "fp", "fn", "p", "r", "f1")))


def validate(reports: DataFrame, judges: bool = True) -> DataFrame:
    """Report keys with ``numeric``, ``temporal`` and, with judges, their scores; metrics also as top-level columns.

    Judges read sentences, so with them sentences are parsed, once, and a text's mentions are those of its
    sentences: no mention goes beyond the end of one.
    """
    keys = [c for c in reports.columns if c not in ("cells", "text")]
    if not judges:
        return _scored(with_mentions(reports), keys, [])
    out = reports.withColumn("claims", judging.claims(F.col("text"), F.col("cells")))
    out = out.withColumn("numbers", F.flatten(F.transform("claims", lambda c: c["numbers"]))).withColumn("dates", F.flatten(F.transform("claims", lambda c: c["dates"])))
    return _scored(out, keys, [judging.judged(F.col("claims"), F.col("text"), F.col("cells")).alias("judge")])


def validate_with(reports: DataFrame, backend, grounding: str = "source") -> DataFrame:
    """``validate`` with a model as judge and as first parser of dates; the rules of dates are its fallback."""
    from ..plans import roles

    keys = [c for c in reports.columns if c not in ("cells", "text")]
    read = roles.primary_dates(reports, backend)
    rules = temporal.parse_dates(F.col("text"))
    read = read.withColumn("dates", F.when(F.col("primary").isNotNull(), temporal.parse_dates(F.col("text"), F.col("primary"))).otherwise(rules))
    read = read.withColumn("numbers", numeric.parse_numbers(F.col("text"))).drop("primary")
    judges = roles.judge_texts(reports, backend, grounding=grounding).select(*keys, "judge")
    return _scored(read, keys, []).join(judges, keys, "left")
