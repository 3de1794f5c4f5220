"""Matching of what a text says with what its source row says: true and false positives, P, R, F1."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .binding import let

#: Relative tolerance of numbers.
TOLERANCE = "0.001"


def prf(tp: Column, found: Column, truth: Column) -> Column:
    """tp, fp, fn with precision, recall and F1; what is undefined is null."""
    return let(
        tp.cast("int"), found.cast("int"), truth.cast("int"),
        lambda tp, found, truth: F.struct(
            tp.alias("tp"), (found - tp).alias("fp"), (truth - tp).alias("fn"),
            F.try_divide(tp.cast("double"), found.cast("double")).alias("p"), F.try_divide(tp.cast("double"), truth.cast("double")).alias("r"),
            F.try_divide(2.0 * tp, (found + truth).cast("double")).alias("f1"),
        ),
    )


def within(truth: Column, found: Column, rel: str = TOLERANCE) -> Column:
    """Equal up to a share of the true value; a true zero needs equality."""
    return F.abs(truth - found) <= F.abs(truth) * F.lit(rel).cast("decimal(4,3)")


def paired(truth: Column, found: Column, rel: str = TOLERANCE) -> Column:
    """Size of the largest one-to-one pairing of two arrays of decimals within the tolerance.

    Both sorted; the ends of the tolerance range rise with the value, so pairing in order is best.
    """

    def merged(a: Column, b: Column) -> Column:
        def step(s, _):
            def move(x, y):
                over = x.isNull() | y.isNull()
                hit = ~over & within(x, y, rel)
                return F.struct(
                    (s["i"] + F.when(~over & (hit | (y >= x)), 1).otherwise(0)).alias("i"), (s["j"] + F.when(~over & (hit | (y < x)), 1).otherwise(0)).alias("j"), (s["tp"] + F.when(hit, 1).otherwise(0)).alias("tp")
                )

            return let(F.try_element_at(a, s["i"]), F.try_element_at(b, s["j"]), move)

        steps = F.sequence(F.lit(1), F.greatest(F.size(a) + F.size(b), F.lit(1)))
        start = F.struct(F.lit(1).alias("i"), F.lit(1).alias("j"), F.lit(0).alias("tp"))
        # equal arrays, the usual case, pair as they are, and so do those whose numbers are all near in order
        near = (F.size(a) == F.size(b)) & F.forall(F.zip_with(a, b, lambda x, y: within(x, y, rel)), lambda hit: hit)
        return F.when(a == b, F.size(a)).when(near, F.size(a)).otherwise(F.aggregate(steps, start, step, lambda s: s["tp"]))

    # a null pairs with nothing; sorted by value without a comparing function, which would be interpreted
    ordered = lambda x: F.sort_array(F.filter(x, lambda v: v.isNotNull()))
    return let(ordered(truth), ordered(found), merged)


def match_numbers(truth: Column, found: Column, mode: str = "bag", rel: str = TOLERANCE, units: bool = False) -> Column:
    """``bag``: one-to-one with repetitions; ``set``: one-to-one of distinct values; ``occurrence``: each
    side asks whether the other has a partner.  With ``units`` both arrays hold structs of value and
    unit, and only equal units pair."""
    return let(truth, found, lambda t, f: _matched(t, f, mode, rel, units))


def _matched(truth: Column, found: Column, mode: str, rel: str, units: bool) -> Column:
    if units:
        tp = F.lit(0)
        for unit in ("usd", "percent", "count"):
            of = lambda x, u=unit: F.transform(F.filter(x, lambda m: m["unit"] == u), lambda m: m["value"])
            tp = tp + paired(of(truth), of(found), rel)
        return prf(tp, F.size(found), F.size(truth))
    if mode == "set":
        return let(F.array_distinct(truth), F.array_distinct(found), lambda t, f: prf(paired(t, f, rel), F.size(f), F.size(t)))
    if mode == "bag":
        return prf(paired(truth, found, rel), F.size(found), F.size(truth))
    hit_found = F.size(F.filter(found, lambda y: F.exists(truth, lambda x: within(x, y, rel))))
    hit_truth = F.size(F.filter(truth, lambda x: F.exists(found, lambda y: within(x, y, rel))))

    def scored(hf, ht, nf, nt):
        p, r = F.try_divide(hf.cast("double"), nf.cast("double")), F.try_divide(ht.cast("double"), nt.cast("double"))
        return F.struct(ht.cast("int").alias("tp"), (nf - hf).cast("int").alias("fp"), (nt - ht).cast("int").alias("fn"), p.alias("p"), r.alias("r"), F.try_divide(2 * p * r, p + r).alias("f1"))

    return let(hit_found, hit_truth, F.size(found), F.size(truth), scored)


def _count(values: Column, x: Column) -> Column:
    return F.size(F.filter(values, lambda y: y == x))


def match_dates(truth: Column, found: Column, mode: str = "bag") -> Column:
    """``bag`` counts repetitions, ``set`` does not; ``granular`` leaves out of the count a coarser
    mention (a year, quarter or month) that a true date falls into."""

    def matched(truth, found):
        if mode == "granular":
            found = F.filter(found, lambda y: F.array_contains(truth, y) | ~F.exists(truth, lambda x: _covers(y, x)))
        if mode == "set":
            truth, found = F.array_distinct(truth), F.array_distinct(found)
        counted = lambda t, f: F.aggregate(F.array_distinct(t), F.lit(0), lambda acc, x: acc + F.least(_count(t, x), _count(f, x)))
        # equal arrays, the usual case, agree as they are
        tp = lambda t, f: F.when((t == f) & F.forall(t, lambda x: x.isNotNull()), F.size(t)).otherwise(counted(t, f))
        return let(truth, found, lambda t, f: prf(tp(t, f), F.size(f), F.size(t)))

    return let(truth, found, matched)


def _covers(coarse: Column, day: Column) -> Column:
    quarter = F.concat(F.substring(day, 1, 4), F.lit("-Q"), F.ceil(F.substring(day, 6, 2).try_cast("int") / 3).cast("string"))
    return (F.length(coarse) < F.length(day)) & (day.startswith(coarse) | (coarse == quarter))


def cell_coverage(cells: Column, text: Column, numbers: Column, dates: Column) -> Column:
    """Share of the cells that are not null whose value occurs in the text, whatever their kind.

    A number in the text stands for one cell: pairing is one-to-one, so a key near a price is not the price as
    well.  Numeric cells that no number is near, as their surface was not read as one, count if it is written.
    """

    def share(present, text, numbers, dates):
        amounts = F.filter(present, lambda c: c["num"].isNotNull())
        unread = F.filter(amounts, lambda c: text.contains(c["surface"]) & ~F.exists(numbers, lambda n: within(c["num"], n)))
        others = F.filter(
            present,
            lambda c: c["num"].isNull() & F.when(c["day"].isNotNull(), F.array_contains(dates, c["day"].cast("string"))).otherwise(text.contains(c["surface"])),
        )
        hits = paired(F.transform(amounts, lambda c: c["num"]), numbers) + F.size(unread) + F.size(others)
        return F.try_divide(hits.cast("double"), F.size(present).cast("double"))

    return let(F.filter(cells, lambda c: c["surface"].isNotNull()), text, numbers, dates, share)


def surface_overlap(cells: Column, text: Column) -> Column:
    """Baseline: share of the distinct tokens of all cells that are tokens of the text."""
    tokens = lambda s: F.array_distinct(F.filter(F.split(F.regexp_replace(F.lower(s), r"\.( |$)", " "), r"[^a-z0-9.#]+"), lambda t: t != ""))
    own = tokens(F.array_join(F.transform(F.filter(cells, lambda c: c["surface"].isNotNull()), lambda c: c["surface"]), " "))
    return let(own, lambda own: F.try_divide(F.size(F.array_intersect(own, tokens(text))).cast("double"), F.size(own).cast("double")))
