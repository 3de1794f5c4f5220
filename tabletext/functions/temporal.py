"""Dates in text: found by ordered patterns, brought to one form, matched as bags.

Patterns stay within what both Java and linear-time engines understand; longer forms come first, so
a year inside a date is not found twice.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .binding import let, surplus

MONTH = r"(?:January|February|March|April|May|June|July|August|September|October|November|December)"
#: Longest first.  A bare year counts only after a word that says it is one.
FORMS = (
    r"\b\d{4}-\d{2}-\d{2}\b",
    r"\b\d{1,2}/\d{1,2}/(?:\d{4}|\d{2})\b",
    rf"\b{MONTH} \d{{1,2}}, \d{{4}}\b",
    rf"\b\d{{1,2}} {MONTH} \d{{4}}\b",
    r"\b(?:first|second|third|fourth|1st|2nd|3rd|4th) quarter of \d{4}\b",
    r"\b\d{4} Q[1-4]\b",
    r"\bQ[1-4] \d{4}\b",
    rf"\b{MONTH} \d{{4}}\b",
    r"\b(?:fiscal year|calendar year|fiscal|year|in|of|during|since) (?:19|20)\d{2}\b",
)
PATTERN = "|".join(FORMS)
LONG = rf"^{MONTH} \d{{1,2}}, \d{{4}}\z"
#: ``PATTERN`` for Java alone: the forms by their first character, so that most places of a text fail at one look.
#: Forms that can start at one place keep their order, so the matches are the same.
SCAN = (
    rf"(?=[0-9])\b(?:\d{{4}}-\d{{2}}-\d{{2}}\b|\d{{1,2}}/\d{{1,2}}/(?:\d{{4}}|\d{{2}})\b|\d{{1,2}} {MONTH} \d{{4}}\b|(?:1st|2nd|3rd|4th) quarter of \d{{4}}\b|\d{{4}} Q[1-4]\b)"
    rf"|(?=[JFMASONDQ])\b(?:{MONTH} (?:\d{{1,2}}, \d{{4}}|\d{{4}})\b|Q[1-4] \d{{4}}\b)"
    r"|(?=[cdfiosty])\b(?:(?:first|second|third|fourth) quarter of \d{4}\b|(?:fiscal year|calendar year|fiscal|year|in|of|during|since) (?:19|20)\d{2}\b)"
)
FOLLOWING = r"\bthe following (?:quarter|month|year)\b"

MENTIONS = "array<struct<value:string,type:string,text:string>>"


def _month(name: Column) -> Column:
    return ((F.instr(F.lit("janfebmaraprmayjunjulaugsepoctnovdec"), F.lower(F.substring(name, 1, 3))) + 2) / 3).cast("int")


def _pad(x: Column, n: int = 2) -> Column:
    return F.lpad(x.cast("string"), n, "0")


def _group(s: Column, pattern: str, i: int = 1) -> Column:
    return F.regexp_extract(s, pattern, i)


def normalise_date(s: Column) -> Column:
    """value and type of one surface form; null value if it is no date."""
    # by far the commonest form has one look at all of it, and its parts by their places
    usual = let(F.split(s, "[ ,]+"), lambda part: F.concat(part[2], F.lit("-"), _pad(_month(part[0])), F.lit("-"), _pad(part[1])))
    named = F.struct(usual.alias("value"), F.lit("date").alias("type"), s.alias("text"))
    return F.when(s.rlike(LONG), named).otherwise(_normalised(s))


def _normalised(s: Column) -> Column:
    us, long, day_first = r"^(\d{1,2})/(\d{1,2})/(\d{2,4})$", rf"^({MONTH}) (\d{{1,2}}), (\d{{4}})$", rf"^(\d{{1,2}}) ({MONTH}) (\d{{4}})$"
    year = _group(s, us, 3)
    ordinal = (F.instr(F.lit("firsecthifou1st2nd3rd4th"), F.substring(s, 1, 3)) - 1) / 3
    day = (
        F.when(s.rlike(r"^\d{4}-\d{2}-\d{2}$"), s)
        .when(s.rlike(us), F.concat(F.when(F.length(year) == 2, F.concat(F.lit("20"), year)).otherwise(year), F.lit("-"), _pad(_group(s, us, 1)), F.lit("-"), _pad(_group(s, us, 2))))
        .when(s.rlike(long), F.concat(_group(s, long, 3), F.lit("-"), _pad(_month(_group(s, long, 1))), F.lit("-"), _pad(_group(s, long, 2))))
        .when(s.rlike(day_first), F.concat(_group(s, day_first, 3), F.lit("-"), _pad(_month(_group(s, day_first, 2))), F.lit("-"), _pad(_group(s, day_first, 1))))
    )
    quarter = (
        F.when(s.rlike(r" quarter of "), F.concat(_group(s, r"(\d{4})$"), F.lit("-Q"), (ordinal.cast("int") % 4 + 1).cast("string")))
        .when(s.rlike(r"^\d{4} Q[1-4]$"), F.concat(F.substring(s, 1, 4), F.lit("-"), F.substring(s, 6, 2)))
        .when(s.rlike(r"^Q[1-4] \d{4}$"), F.concat(F.substring(s, 4, 4), F.lit("-"), F.substring(s, 1, 2)))
    )
    month = F.when(s.rlike(rf"^{MONTH} \d{{4}}$"), F.concat(_group(s, r"(\d{4})$"), F.lit("-"), _pad(_month(s))))
    only_year = F.when(s.rlike(r"^[a-z][a-z ]* \d{4}$"), _group(s, r"(\d{4})$"))
    kind = lambda v: F.when(F.length(v) == 10, "date").when(v.contains("Q"), "quarter").when(F.length(v) == 7, "month").when(v.isNotNull(), "year")
    return let(F.coalesce(day, quarter, month, only_year), lambda v: F.struct(v.alias("value"), kind(v).alias("type"), s.alias("text")))


def parse_dates(text: Column, primary: Column | None = None, anchor: Column | None = None) -> Column:
    """All date mentions of a text in order, as structs of value, type and text.

    ``primary`` is what a context-aware parser found (the same structs, values may be null); where it
    resolved a mention, its value stands, else the rules decide.  ``anchor`` is a date that "the
    following quarter, month or year" is counted from.
    """
    surfaces = F.regexp_extract_all(text, F.lit(SCAN), F.lit(0))
    if primary is None:
        found = F.filter(F.transform(surfaces, normalise_date), lambda m: m["value"].isNotNull())
    else:
        resolved = F.transform(primary, lambda m: let(normalise_date(m["text"]), lambda n: F.struct(F.coalesce(m["value"], n["value"]).alias("value"), F.coalesce(m["type"], n["type"]).alias("type"), m["text"].alias("text"))))
        # what the primary parser did not see, or saw less often, comes from the rules
        rest = F.transform(surplus(surfaces, F.transform(primary, lambda m: m["text"])), normalise_date)
        found = F.filter(F.concat(resolved, rest), lambda m: m["value"].isNotNull())
    if anchor is not None:
        phrases = F.regexp_extract_all(text, F.lit(FOLLOWING), F.lit(0))
        found = F.concat(found, F.transform(phrases, lambda p: _following(p, anchor)))
    return F.coalesce(found, F.expr(f"cast(array() as {MENTIONS})"))


def _following(phrase: Column, anchor: Column) -> Column:
    later = F.add_months(anchor, 3)
    quarter = F.concat(F.year(later).cast("string"), F.lit("-Q"), F.quarter(later).cast("string"))
    month = F.date_format(F.add_months(anchor, 1), "yyyy-MM")
    year = (F.year(anchor) + 1).cast("string")
    kind = F.regexp_extract(phrase, r"(quarter|month|year)$", 1)
    return F.struct(F.when(kind == "quarter", quarter).when(kind == "month", month).otherwise(year).alias("value"), kind.alias("type"), phrase.alias("text"))


def values(mentions: Column) -> Column:
    return F.transform(mentions, lambda m: m["value"])


def truth_dates(cells: Column) -> Column:
    """Normal forms of all date cells; text cells go through the same parser, others give nothing."""
    days = F.transform(F.filter(cells, lambda c: c["day"].isNotNull()), lambda c: c["day"].cast("string"))
    texts = F.filter(cells, lambda c: (c["kind"] == "text") & c["surface"].isNotNull())
    return F.concat(days, F.flatten(F.transform(texts, lambda c: values(parse_dates(c["surface"])))))


def mask_dates(text: Column) -> Column:
    return F.regexp_replace(text, SCAN, " ")
