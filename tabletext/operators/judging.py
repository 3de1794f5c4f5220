"""Rubric judges as rules over claims.

A claim is a sentence.  A mention is grounded if it equals a cell; a claim with an ungrounded mention
is unsupported; a claim that names a cell's label next to mentions of its kind, none of which is the
cell's value, is contradicted.  The share of good claims gives a level from 1 to 5.  These are scores of rules, not of a language model, and are not to be read as such.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import fidelity, numeric, temporal
from ..functions.binding import let
from .generation import sentences

#: dimension, level, least share of good claims, what it means
RUBRICS = (
    ("factuality", 5, 1.0, "no claim is contradicted by the source row"),
    ("factuality", 4, 0.9, "one claim in ten, and a side matter, is contradicted"),
    ("factuality", 3, 0.7, "details are off; the main statements hold"),
    ("factuality", 2, 0.4, "central values are wrong"),
    ("factuality", 1, 0.0, "more claims are wrong than right"),
    ("hallucination", 5, 1.0, "everything said comes from the row or names its source"),
    ("hallucination", 4, 0.9, "a small detail has no ground"),
    ("hallucination", 3, 0.7, "some details have no ground"),
    ("hallucination", 2, 0.4, "many points cannot be traced"),
    ("hallucination", 1, 0.0, "most of the details are made up"),
    ("coherence", 5, 1.0, "follows the plan's order without a break"),
    ("coherence", 4, 0.9, "a slight jump"),
    ("coherence", 3, 0.7, "some jumps or repetitions, still readable"),
    ("coherence", 2, 0.4, "often out of order"),
    ("coherence", 1, 0.0, "no order to be seen"),
)
DIMENSIONS = ("factuality", "hallucination", "coherence")
#: What a domain asks instead of the general rubric: dimension, level, least share of good claims
DOMAIN_RUBRICS = {
    "finance": (("factuality", 4, 0.95), ("factuality", 3, 0.85), ("factuality", 2, 0.6), ("hallucination", 4, 0.95), ("hallucination", 3, 0.85)),
    "narrative": (("coherence", 4, 0.8), ("coherence", 3, 0.5), ("coherence", 2, 0.25)),
}
ATTRIBUTION = r"(?i)according to|as stated in|as reported by"


def rubric_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(RUBRICS), "dimension string, level int, least_share double, meaning string")


def domain_rubric_table(spark: SparkSession, domains: dict = DOMAIN_RUBRICS) -> DataFrame:
    """domain, dimension, level, least_share: all fifteen steps of each domain, its own in place of the general ones."""
    rows = []
    for name, own in domains.items():
        steps = {(d, level): share for d, level, share, _ in RUBRICS} | {(d, level): share for d, level, share in own}
        rows += [(name, d, level, share) for (d, level), share in steps.items()]
    return spark.createDataFrame(rows, "domain string, dimension string, level int, least_share double")


def rubric_level(share: Column) -> Column:
    return let(share, lambda share: F.when(share >= 1, 5).when(share >= 0.9, 4).when(share >= 0.7, 3).when(share >= 0.4, 2).otherwise(1))


def _label(name: Column) -> Column:
    plain = F.when(name.contains("_value"), F.regexp_replace(name, "_value$", "")).otherwise(name)
    return F.replace(plain, F.lit("_"), F.lit(" "))


def claims(text: Column, cells: Column) -> Column:
    """Structs pos, text, supported, contradicted, ungrounded, reason, numbers, dates (the mentions): a sentence each."""

    def verdict(s, i, n, d, numbers, dates, known, days, labelled):
        loose = F.exists(numbers, lambda n: ~F.exists(known, lambda c: fidelity.within(c, n))) | F.exists(dates, lambda d: ~F.array_contains(days, d))
        loose = loose & ~s.rlike(ATTRIBUTION)
        wrong = F.exists(
            labelled,
            lambda c: s.contains(c["words"])
            & F.when(c["num"].isNotNull(), (F.size(numbers) > 0) & ~F.exists(numbers, lambda n: fidelity.within(c["num"], n)))
            .when(c["day"].isNotNull(), (F.size(dates) > 0) & ~F.array_contains(dates, c["day"].cast("string")))
            .otherwise(F.lit(False)),
        )
        reason = lambda wrong, loose: F.when(wrong, "a named cell has another value").when(loose, "a mention is in no cell").otherwise("all mentions are in cells")
        return let(wrong, loose, lambda w, x: F.struct(i.alias("pos"), s.alias("text"), (~x & ~w).alias("supported"), w.alias("contradicted"), x.alias("ungrounded"), reason(w, x).alias("reason"), n.alias("numbers"), d.alias("dates")))

    def one(s: Column, i: Column, known: Column, days: Column, labelled: Column) -> Column:
        return let(numeric.parse_numbers(s), temporal.parse_dates(s), lambda n, d: let(numeric.values(n), temporal.values(d), lambda ns, ds: verdict(s, i, n, d, ns, ds, known, days, labelled)))

    # labels are made once a cell, not once a cell and sentence
    labelled = F.transform(cells, lambda c: F.struct(F.concat(F.lit(" "), _label(c["name"]), F.lit(" ")).alias("words"), c["num"].alias("num"), c["day"].alias("day")))
    return let(numeric.truth_numbers(cells), temporal.truth_dates(cells), labelled, lambda known, days, labelled: F.transform(sentences(text), lambda s, i: one(s, i, known, days, labelled)))


def claim_table(reports: DataFrame) -> DataFrame:
    keys = [c for c in reports.columns if c not in ("cells", "text")]
    return reports.select(*keys, F.inline(claims(F.col("text"), F.col("cells"))).alias("pos", "claim", "supported", "contradicted", "ungrounded", "reason", "numbers", "dates")).drop("numbers", "dates")


def _share(claims: Column, bad: str) -> Column:
    return let(claims, lambda claims: 1.0 - F.size(F.filter(claims, lambda c: c[bad])) / F.size(claims))


def coherence_share(text: Column, cells: Column) -> Column:
    """Mean of: neighbours in the plan's order that are so in the text too; sentences that are not repeated."""
    places = F.filter(F.transform(F.filter(cells, lambda c: c["surface"].isNotNull()), lambda c: F.instr(text, F.concat(F.lit(" "), _label(c["name"]), F.lit(" ")))), lambda p: p > 0)

    def share(places, own):
        steps = F.size(places) - 1
        ahead = F.filter(F.sequence(F.lit(1), F.greatest(steps, F.lit(1))), lambda i: F.try_element_at(places, i + 1) >= F.try_element_at(places, i))
        ordered = F.when(steps > 0, F.size(ahead) / steps).otherwise(1.0)
        return (ordered + F.size(F.array_distinct(own)) / F.size(own)) / 2

    return let(places, sentences(text), share)


def judge_hallucination(text: Column, cells: Column) -> Column:
    return rubric_level(_share(claims(text, cells), "ungrounded"))


def judge_factuality(text: Column, cells: Column, grounding: str = "source") -> Column:
    """Against the source row; judging by general knowledge needs a model (``plans.roles.judge_texts``)."""
    if grounding != "source":
        raise ValueError("judging by general knowledge needs a model backend")
    return rubric_level(_share(claims(text, cells), "contradicted"))


def judge_coherence(text: Column, cells: Column) -> Column:
    return rubric_level(coherence_share(text, cells))


def judge(text: Column, cells: Column) -> Column:
    """All three scores, the overall mean, the supported share of claims and the self-consistency flag."""
    return judged(claims(text, cells), text, cells)


def judged(found: Column, text: Column, cells: Column) -> Column:
    """``judge`` from the claims of the text."""

    def scored(found):
        supported = F.size(F.filter(found, lambda x: x["supported"])) / F.size(found)
        levels = (rubric_level(_share(found, "contradicted")), rubric_level(_share(found, "ungrounded")), judge_coherence(text, cells), supported)
        return let(*levels, lambda f, h, c, s: F.struct(f.alias("factuality"), h.alias("hallucination"), c.alias("coherence"), text_quality(f, h, c).alias("overall"), s.alias("supported_share"), self_consistency(F.least(f, h), s).alias("consistent")))

    return let(found, scored)


def judge_in_domain(reports: DataFrame, rubrics: DataFrame, domain: str = "domain") -> DataFrame:
    """The three scores by the rubric of each report's domain; a domain without a rubric has the general one.

    Rubrics are declared, fifteen steps a domain, so they are broadcast.
    """
    steps = rubrics.groupBy(F.col("domain").alias("__domain")).agg(F.collect_list(F.struct("dimension", "level", "least_share")).alias("__steps"))
    shares = let(claims(F.col("text"), F.col("cells")), lambda c: F.struct(_share(c, "contradicted").alias("factuality"), _share(c, "ungrounded").alias("hallucination"), coherence_share(F.col("text"), F.col("cells")).alias("coherence")))

    def level(d: str) -> Column:
        share = F.col("__shares")[d]
        passed = F.filter("__steps", lambda s: (s["dimension"] == d) & (share >= s["least_share"]))
        return F.coalesce(F.array_max(F.transform(passed, lambda s: s["level"])), rubric_level(share)).alias(d)

    judged = reports.withColumn("__shares", shares).join(F.broadcast(steps), F.col(domain) == F.col("__domain"), "left")
    return judged.select("*", *(level(d) for d in DIMENSIONS)).drop("__shares", "__steps", "__domain")


def text_quality(factuality: Column, hallucination: Column, coherence: Column) -> Column:
    return (factuality + hallucination + coherence) / 3.0


def self_consistency(score: Column, supported_share: Column, max_gap: int = 1) -> Column:
    """Whether a score is near what its own claims imply."""
    return F.abs(score - rubric_level(supported_share)) <= max_gap


def judge_agreement(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """n, exact share, mean gap and Cohen's kappa of two columns of labels, from their contingency table."""
    cells = pairs.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count("*").alias("n"))
    rows, cols = cells.groupBy("a").agg(F.sum("n").alias("r")), cells.groupBy("b").agg(F.sum("n").alias("c"))
    chance = rows.join(cols, rows["a"] == cols["b"]).agg(F.coalesce(F.sum(F.col("r") * F.col("c")), F.lit(0)).cast("double").alias("chance"))
    total = cells.agg(F.sum("n").alias("n"), F.coalesce(F.sum(F.when(F.col("a") == F.col("b"), F.col("n"))), F.lit(0)).alias("same"), F.sum(F.abs(F.col("a") - F.col("b")) * F.col("n")).alias("gap"))
    both = total.join(chance)  # one row each
    po, pe = F.col("same") / F.col("n"), F.col("chance") / (F.col("n").cast("double") * F.col("n"))
    return both.select("n", po.alias("exact_share"), (F.col("gap") / F.col("n")).alias("mean_gap"), F.try_divide(po - pe, 1 - pe).alias("kappa"))
