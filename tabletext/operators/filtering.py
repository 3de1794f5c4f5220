"""Dropping weak reports by a threshold on the weakest metric, and what that does to the others."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..storage import written
from .validation import METRICS

TAUS = ("1.00", "0.95", "0.90", "0.85", "0.80", "0.75", "0.70")


def metric_means(v: DataFrame, by: str = "dataset") -> DataFrame:
    """by, metric, mean: a row a metric; undefined values are left out of the means."""
    wide = v.groupBy(by).agg(*(F.avg(m).alias(m) for m in METRICS))
    return wide.unpivot([by], list(METRICS), "metric", "mean")


def weakest_metric(v: DataFrame, by: str = "dataset") -> DataFrame:
    """The lowest of the four fidelity metrics of each dataset; ties go to the first name."""
    found = metric_means(v, by).where("mean is not null")
    return found.groupBy(by).agg(F.min(F.struct("mean", "metric")).alias("m")).select(by, F.col("m.metric").alias("metric"), F.col("m.mean").alias("mean"))


def _undefined(value: Column, policy: str) -> Column:
    """``pass``, ``one``: counts as perfect; ``zero``, ``drop``: counts as none at all."""
    return F.coalesce(value, F.lit({"pass": 1.0, "one": 1.0, "zero": 0.0, "drop": -1.0}[policy]))


def score_of(kind: str, on: str = "either", undefined: str = "pass") -> Column:
    """What is held against the threshold: precision, recall, or the lesser of both."""
    p, r = (_undefined(F.col(f"{kind}_{m}"), undefined) for m in ("p", "r"))
    return {"precision": p, "recall": r, "either": F.least(p, r)}[on]


def filter_reports(v: DataFrame, kind: str, tau: str | float, on: str = "either", undefined: str = "pass") -> DataFrame:
    """Reports at the threshold or above it; ``kind`` is numeric or temporal."""
    return v.where(score_of(kind, on, undefined).cast("decimal(9,6)") >= F.lit(str(tau)).cast("decimal(9,6)"))


def filter_weakest(v: DataFrame, tau: str | float, by: str = "dataset", on: str = "either", undefined: str = "pass") -> DataFrame:
    """Each dataset is filtered on its own weakest metric; the choice is a row a dataset.

    The scores are read twice, for the choice and for the filter, so they are written before.
    """
    v = written(v, "scores")
    weakest = weakest_metric(v, by).select(F.col(by).alias("__by"), F.split("metric", "_")[0].alias("__kind"))
    joined = v.join(F.broadcast(weakest), F.col(by) == F.col("__by"), "left")
    score = F.when(F.col("__kind") == "numeric", score_of("numeric", on, undefined)).otherwise(score_of("temporal", on, undefined))
    return joined.where(score.cast("decimal(9,6)") >= F.lit(str(tau)).cast("decimal(9,6)")).drop("__by", "__kind")


def reweigh(v: DataFrame, by: str = "dataset") -> DataFrame:
    """Macro averages of all metrics on what is given."""
    metrics = [f"{k}_{m}" for k in ("numeric", "temporal") for m in ("p", "r", "f1")]
    return v.groupBy(by).agg(F.count("*").alias("n_reports"), *(F.avg(m).alias(m) for m in metrics))


def tau_sweep(v: DataFrame, kind: str = "temporal", taus: tuple[str, ...] = TAUS, by: str = "dataset", on: str = "either", undefined: str = "pass", include_unfiltered: bool = True) -> DataFrame:
    """by, tau, n_reports, retained_share and the mean of each metric on what each threshold keeps.

    One scan and one aggregation: counts and sums of every threshold side by side, a row a dataset.
    """
    score = score_of(kind, on, undefined).cast("decimal(9,6)")
    steps = [(t, score >= F.lit(t).cast("decimal(9,6)")) for t in taus] + ([("0.00", F.lit(True))] if include_unfiltered else [])
    rows = []
    for t, passed in steps:
        n = F.count_if(passed)
        means = [F.avg(F.when(passed, F.col(m))).alias(f"avg_{m}") for m in METRICS]
        rows.append(F.struct(F.lit(t).cast("decimal(3,2)").alias("tau"), n.alias("n_reports"), F.try_divide(n.cast("double"), F.count("*").cast("double")).alias("retained_share"), *means))
    return v.groupBy(by).agg(F.array(*rows).alias("rows")).select(by, F.inline("rows"))
