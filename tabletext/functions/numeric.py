"""Numbers in text: money, percentages and quantities, brought to one decimal form."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from . import temporal
from .binding import let, surplus

#: Identifiers with digits, codes that start with a digit, addresses of machines, phone and card shapes.
IDENTIFIERS = (
    r"[A-Za-z_]+[#_-]*[0-9][A-Za-z0-9#_-]*"
    r"|\b[0-9]+-[A-Za-z][A-Za-z0-9-]*(?: [A-Z]+)?"
    r"|\b[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\b"
    r"|\+?\(?[0-9]{2,4}\)?[ -][0-9]{3,4}[ -][0-9]{3,4}(?:[ -][0-9]{3,4})?"
)
#: ``IDENTIFIERS`` for Java alone: by first character, words looked at from their beginning only (or from the end of the
#: match before) and without going back in them; the matches are the same.
MASKED = (
    r"(?=[A-Za-z_])(?:(?<![A-Za-z_])|\G)[A-Za-z_]++[#_-]*+[0-9][A-Za-z0-9#_-]*+"
    r"|(?=[0-9])\b(?:[0-9]++-[A-Za-z][A-Za-z0-9-]*(?: [A-Z]+)?|[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\.[0-9]{1,3}\b)"
    r"|(?=[+(0-9])\+?\(?[0-9]{2,4}\)?[ -][0-9]{3,4}[ -][0-9]{3,4}(?:[ -][0-9]{3,4})?"
)
#: What any text with such an identifier has, seen from its digits: most texts have none and are left as they are.
SUSPECT = r"[0-9](?:(?<=[A-Za-z_#-][0-9])|-[A-Za-z]|\.[0-9]{1,3}\.[0-9]|\)?[ -][0-9])"
_DIGITS = r"[0-9][0-9,]*(?:\.[0-9]+)?"
PATTERN = rf"\(\$?{_DIGITS}\)|-?\$?{_DIGITS}(?:[eE][+-]?[0-9]+\b)?(?: ?%| percent\b)?(?: (?:thousand|million|billion|trillion)\b)?"
#: The same, at places where a number can start.
SCAN = rf"(?=[-$(0-9])(?:{PATTERN})"
#: The usual surface: a sign, a currency, digits, a percent sign.
PLAIN = rf"^-?\$?{_DIGITS}%?\z"

MENTIONS = "array<struct<value:decimal(24,6),unit:string,surface:string>>"


def mask_non_numeric(text: Column) -> Column:
    """Dates and digits that belong to identifiers give way to spaces."""
    return let(temporal.mask_dates(text), lambda s: F.when(s.rlike(SUSPECT), F.regexp_replace(s, MASKED, " ")).otherwise(s))


def normalise_number(s: Column, context: Column | None = None) -> Column:
    """value, unit and surface of one surface form.

    Percentages become fractions, magnitude words multiply, parentheses are negative, scientific
    notation is expanded.  With ``context`` (the words before it) a bare number after a currency word
    counts as money.  The usual surface needs one look at its form; all others are taken apart.
    """
    odd = _normalised(s, context)
    if context is not None:
        return odd

    def usual():
        digits = F.translate(s, "-$,%", "").try_cast("decimal(24,6)")
        signed = lambda v: F.when(s.startswith("-"), -v).otherwise(v)
        percent = s.endswith("%")
        value = F.when(percent, (signed(digits) / F.lit(100).cast("decimal(3,0)")).try_cast("decimal(24,6)")).otherwise(signed(digits))
        return F.struct(value.alias("value"), F.when(percent, "percent").when(s.contains("$"), "usd").otherwise("count").alias("unit"), s.alias("surface"))

    return F.when(s.rlike(PLAIN), usual()).otherwise(odd)


def _normalised(s: Column, context: Column | None = None) -> Column:
    plain = F.regexp_replace(F.regexp_extract(s, rf"{_DIGITS}(?:[eE][+-]?[0-9]+)?", 0), ",", "")
    value = plain.try_cast("decimal(24,6)")
    sign = F.when(s.rlike(r"^\(|^-|^\$-"), F.lit(-1)).otherwise(F.lit(1))
    scale = F.when(s.endswith("thousand"), F.lit(10**3)).when(s.endswith("million"), F.lit(10**6)).when(s.endswith("billion"), F.lit(10**9)).when(s.endswith("trillion"), F.lit(10**12)).otherwise(F.lit(1))
    percent = s.rlike(r"%|percent")
    money = s.contains("$")
    if context is not None:
        money = money | F.lower(context).rlike(r"(?:usd|dollars?|eur|price|revenue|amount) *$")
    whole = (value * sign * scale.cast("decimal(14,0)")).try_cast("decimal(24,6)")
    value = let(whole, lambda whole: F.when(percent, (whole / F.lit(100).cast("decimal(3,0)")).try_cast("decimal(24,6)")).otherwise(whole))
    return F.struct(value.alias("value"), F.when(percent, "percent").when(money, "usd").otherwise("count").alias("unit"), s.alias("surface"))


def parse_numbers(text: Column, masked: bool = False, tagger: Column | None = None) -> Column:
    """All number mentions of a text in order.

    ``tagger`` holds surfaces that a trained recogniser found; those that the patterns miss join in, counted as
    bags: what both found once is there once, what the tagger found once more is there once more.
    """
    source = text if masked else mask_non_numeric(text)
    surfaces = F.regexp_extract_all(source, F.lit(SCAN), F.lit(0))
    if tagger is not None:
        surfaces = let(surfaces, tagger, lambda own, more: F.concat(own, surplus(more, own)))
    found = F.filter(F.transform(surfaces, lambda s: normalise_number(s)), lambda m: m["value"].isNotNull())
    return F.coalesce(found, F.expr(f"cast(array() as {MENTIONS})"))


def values(mentions: Column) -> Column:
    return F.transform(mentions, lambda m: m["value"])


def truth_numbers(cells: Column) -> Column:
    """Values of all numeric cells, those of identifiers with a numeric type as well."""
    return F.transform(F.filter(cells, lambda c: c["num"].isNotNull()), lambda c: c["num"])


def truth_units(cells: Column) -> Column:
    kept = F.filter(cells, lambda c: c["num"].isNotNull())
    unit = lambda c: F.when(c["kind"] == "money", "usd").when(c["kind"] == "ratio", "percent").otherwise("count")
    return F.transform(kept, lambda c: F.struct(c["num"].alias("value"), unit(c).alias("unit")))
