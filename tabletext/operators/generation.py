"""Reports: a passage for each row and report type, and controlled damage to them.

The plan becomes literal expressions, so one scan yields the reports of all types and reads no other
columns.  Choices of wording come from digests of row and column: the same row always gives the same
text, whatever the partitioning and however often a task runs.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.planning import Plan, PlanColumn, ReportType
from ..sources.tables import spread

CELL = "struct<name:string,kind:string,surface:string,num:decimal(24,6),day:date>"
VERBS = ("is", "was recorded as", "stands at", "came to")
#: Other words for a label, so that the column of a value has to be found, not read off.
SYNONYMS = {
    "total price": ("order total", "amount due"), "order date": ("date of order",), "status": ("state",), "segment": ("market",), "retail price": ("list price",),
    "size": ("dimension",), "extended price": ("line total",), "quantity": ("number of units",), "ship date": ("date of shipment",), "balance": ("account balance",), "revenue": ("earnings",),
}
MONEY = ("price", "balance", "revenue", "cost", "amount")
RATIO = ("discount", "tax", "rate", "share", "ratio")


@dataclass(frozen=True)
class RenderStyle:
    date: str = "long"  # long, us, iso
    magnitude: bool = False  # whole thousands and millions as words
    wording: str = "varied"  # varied, fixed (the template baseline), paraphrased (labels vary too)


def kind_of(f: T.StructField) -> str:
    if isinstance(f.dataType, (T.DateType, T.TimestampType, T.TimestampNTZType)):
        return "date"
    if isinstance(f.dataType, T.IntegralType):
        return "integer"
    if isinstance(f.dataType, T.NumericType):
        return "money" if any(m in f.name for m in MONEY) else "ratio" if any(m in f.name for m in RATIO) else "quantity"
    return "text"


def render_value(c: Column, kind: str, style: RenderStyle = RenderStyle()) -> Column:
    """The surface of a cell; null stays null."""
    if kind == "date":
        forms = {"long": "MMMM d, yyyy", "us": "M/d/yy", "iso": "yyyy-MM-dd"}
        return F.date_format(c, forms[style.date])
    if kind == "integer":
        return c.cast("string")
    if kind == "text":
        return c.cast("string")
    number = c.cast("decimal(24,6)")
    if kind == "ratio":
        return F.concat(F.format_number(number * 100, 2), F.lit("%"))
    sign, size = F.when(number < 0, "-").otherwise(""), F.abs(number)
    prefix = "$" if kind == "money" else ""
    plain = F.format_number(size, 2)
    if style.magnitude:
        words = [(10**9, "billion"), (10**6, "million"), (10**3, "thousand")]
        for unit, word in reversed(words):
            short = F.concat(F.format_number((size / unit).cast("decimal(24,6)"), 2), F.lit(f" {word}"))
            # only where two decimals say it exactly
            plain = F.when((size >= unit) & (size % F.lit(unit // 100) == 0), short).otherwise(plain)
    return F.when(number.isNotNull(), F.concat(sign, F.lit(prefix), plain))


def cell(f: T.StructField, style: RenderStyle = RenderStyle()) -> Column:
    c, kind = F.col(f"`{f.name}`"), kind_of(f)
    num = c.cast("decimal(24,6)") if kind in ("integer", "money", "ratio", "quantity") else F.lit(None).cast("decimal(24,6)")
    day = c.cast("date") if kind == "date" else F.lit(None).cast("date")
    return F.struct(F.lit(f.name).alias("name"), F.lit(kind).alias("kind"), render_value(c, kind, style).alias("surface"), num.alias("num"), day.alias("day"))


def label(name: str) -> str:
    return name.removesuffix("_value").replace("_", " ")


def choice(row_id: Column, name: str, n: int) -> Column:
    """A number below n that depends on the row and a column's name."""
    return (F.conv(F.substring(F.md5(F.concat(row_id, F.lit("|" + name))), 1, 2), 16, 10).cast("int") % n).cast("int")


def _companion(of: PlanColumn, surface: dict[str, Column]) -> Column:
    before = {"period": " for the period ending ", "filing_date": ", filed on ", "unit": ", stated in ", "currency": ", stated in "}[of.companion]
    return F.coalesce(F.concat(F.lit(before), surface[of.name]), F.lit(""))


def passage(row_id: Column, kind: ReportType, fields: dict[str, T.StructField], style: RenderStyle = RenderStyle()) -> Column:
    """The text of one report; sentences of null cells are left out."""
    surface = {c.name: render_value(F.col(f"`{c.name}`"), kind_of(fields[c.name]), style) for c in kind.columns}
    named = [F.concat(F.lit(label(c.name) + " "), surface[c.name]) for c in kind.columns if c.role == "identifier"]
    opening = F.concat(F.lit("This report covers "), F.concat_ws(" and ", *named) if named else F.lit("one row"), F.lit("."))
    sentences = []
    for c in kind.columns:
        if c.role in ("identifier", "companion"):
            continue
        verbs = F.element_at(F.array(*map(F.lit, VERBS)), choice(row_id, c.name, len(VERBS)) + 1) if style.wording != "fixed" else F.lit(VERBS[0])
        words = (label(c.name), *SYNONYMS.get(label(c.name), ())) if style.wording == "paraphrased" else (label(c.name),)
        called = F.element_at(F.array(*map(F.lit, words)), choice(row_id, c.name + "|label", len(words)) + 1) if len(words) > 1 else F.when(row_id.isNotNull(), words[0])
        more = [_companion(x, surface) for x in kind.columns if x.role == "companion" and x.metric == c.name]
        sentences.append(F.concat(F.lit("Its "), called, F.lit(" "), verbs, F.lit(" "), surface[c.name], *more, F.lit(".")))
    return F.concat_ws(" ", opening, *sentences)


def generate(df: DataFrame, plan: Plan, style: RenderStyle = RenderStyle(), dataset: str | None = None, backend=None) -> DataFrame:
    """dataset, table_name, report_type, row_id, cells, text: a row for each row and report type, one scan.

    With a backend (``CachedCalls``) a model writes the texts, from the planned cells of one row alone;
    a report that it failed to write is left out.
    """
    if backend is not None:
        from ..plans import roles

        return roles.write_texts(generate(df, plan, style, dataset).drop("text"), backend).where("text is not null").select("dataset", "table_name", "report_type", "row_id", "cells", "text")
    fields = {f.name: f for f in df.schema.fields}
    df = spread(df)
    reports = [
        F.struct(F.lit(t.name).alias("report_type"), F.array(*(cell(fields[c.name], style) for c in t.columns)).alias("cells"), passage(F.col("row_id"), t, fields, style).alias("text"))
        for t in plan.types
    ]
    table = F.col("table_name") if "table_name" in fields else F.lit(plan.table)
    # the lambda keeps the making of reports out of the whole stage's one method, which would be too large for the JIT; it
    # stands in the generator itself, as an array made below it is made twice, for an inferred filter on its size
    made = F.transform(F.array(*reports), lambda r: r)
    return df.select(F.lit(dataset or plan.table).alias("dataset"), table.alias("table_name"), F.col("row_id").alias("row_id"), F.inline(made)).select("dataset", "table_name", "report_type", "row_id", "cells", "text")


def project_cells(df: DataFrame, plan: Plan) -> DataFrame:
    return generate(df, plan).drop("text")


def build_prompt(cells: Column, role: str = "generate") -> Column:
    """What a model is shown: the planned columns and nothing else."""
    shown = F.transform(F.filter(cells, lambda c: c["surface"].isNotNull()), lambda c: F.struct(c["name"].alias("name"), c["surface"].alias("value")))
    return F.to_json(F.struct(F.lit(role).alias("role"), shown.alias("cells")))


def sentences(text: Column) -> Column:
    return F.split(F.regexp_replace(text, r"\. +([A-Z])", ".\n$1"), "\n")


CORRUPTIONS = ("drop", "beyond", "within", "stray_year", "none")


def corrupt(reports: DataFrame, code: Column | None = None) -> DataFrame:
    """Adds ``damage`` by a number modulo 5: a numeric sentence dropped, a number altered beyond or
    within the tolerance, a stray year added, or nothing.  The number concerned is the first of the
    cells that is not an integer; reports without one are only given stray years."""
    code = F.pmod(F.xxhash64("row_id"), F.lit(5)) if code is None else code
    subject = F.try_element_at(F.filter("cells", lambda c: c["num"].isNotNull() & c["kind"].isin("money", "quantity", "ratio")), F.lit(1))
    altered = lambda by: F.replace(F.col("text"), F.concat(F.lit(" "), subject["surface"]), F.concat(F.lit(" "), _like(subject, by)))
    hole = F.array_join(F.filter(sentences(F.col("text")), lambda s: ~s.contains(F.concat(F.lit(" "), subject["surface"]))), " ")
    has = subject.isNotNull()
    damage = F.when((code == 3), "stray_year").when(has & (code == 0), "drop").when(has & (code == 1), "beyond").when(has & (code == 2), "within").otherwise("none")
    return reports.withColumn("damage", damage).withColumn(
        "text",
        F.when(F.col("damage") == "drop", hole).when(F.col("damage") == "beyond", altered(subject["num"] * F.lit(1.01).cast("decimal(4,2)") + 1)).when(F.col("damage") == "within", altered(subject["num"] * F.lit(1.0005).cast("decimal(6,4)")))
        .when(F.col("damage") == "stray_year", F.concat(F.col("text"), F.lit(" These figures close the fiscal year 2024."))).otherwise(F.col("text")),
    )


def _like(subject: Column, value: Column) -> Column:
    """A number rendered as the cell's kind is."""
    value = value.cast("decimal(24,6)")
    plain = F.concat(F.when(value < 0, "-").otherwise(""), F.when(subject["kind"] == "money", "$").otherwise(""), F.format_number(F.round(F.abs(value), 2), 2))
    return F.when(subject["kind"] == "ratio", F.concat(F.format_number(F.round(value * 100, 2), 2), F.lit("%"))).otherwise(plain)


FURTHER = {5: "repeat", 6: "near", 7: "shuffle"}


def corrupt_further(reports: DataFrame, code: Column) -> DataFrame:
    """``corrupt`` with three more kinds, by a number modulo 8: the first sentence repeated at the end, an estimate
    within the tolerance of the true number added beside it, or the sentences put in another order.  Ways of
    counting (with repetitions or not, one to one or not) and coherence differ on these."""
    subject = F.try_element_at(F.filter("cells", lambda c: c["num"].isNotNull() & c["kind"].isin("money", "quantity", "ratio")), F.lit(1))
    out = corrupt(reports, code)
    kind = F.when(code == 5, "repeat").when((code == 6) & subject.isNotNull(), "near").when(code == 7, "shuffle").otherwise(F.col("damage"))
    again = F.concat_ws(" ", "text", F.element_at(sentences(F.col("text")), 1))
    near = F.concat(F.col("text"), F.lit(" An estimate is "), _like(subject, subject["num"] * F.lit(1.0005).cast("decimal(6,4)")), F.lit("."))
    return out.withColumn("damage", kind).withColumn("text", F.when(F.col("damage") == "repeat", again).when(F.col("damage") == "near", near).when(F.col("damage") == "shuffle", _shuffled(F.col("text"))).otherwise(F.col("text")))


def _shuffled(text: Column) -> Column:
    return F.array_join(F.transform(F.array_sort(F.transform(sentences(text), lambda s: F.struct(F.md5(s).alias("k"), s.alias("s")))), lambda x: x["s"]), " ")


def shuffle_sentences(reports: DataFrame) -> DataFrame:
    """Sentences in the order of their digests: nothing but coherence suffers."""
    return reports.withColumn("text", _shuffled(F.col("text")))


def mix_rows(reports: DataFrame, every: int = 2) -> DataFrame:
    """Appends to every so many a report's text that of another row: the single-row check must fail."""
    from pyspark.sql import Window as W

    other = F.lead("text").over(W.partitionBy("dataset", "table_name", "report_type").orderBy("row_id"))
    return reports.withColumn("__other", other).withColumn("text", F.when((F.pmod(F.xxhash64("row_id"), F.lit(every)) == 0) & F.col("__other").isNotNull(), F.concat_ws(" ", "text", "__other")).otherwise(F.col("text"))).drop("__other")


def single_row(text: Column) -> Column:
    """Whether a passage is about one row: it opens once."""
    return F.size(F.regexp_extract_all(text, F.lit("This report covers "), F.lit(0))) == 1
