"""Source tables: readers, row keys, facts over time, personal data, statistics."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events")


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """Rows of fewer files than there are cores, dealt to all cores; any larger table as it is, without an exchange.

    Reading and writing texts is costly for its bytes, and a small file is one task.
    """
    if df.isStreaming:
        return df
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if 0 < len(df.inputFiles()) < cores else df


def load_any(spark: SparkSession, uri: str, format: str = "parquet", schema=None, bounds: tuple | None = None, **options) -> DataFrame:
    """Any table: parquet, csv, json, jdbc, or ``table`` for one of the catalog.

    ``bounds`` (column, least, greatest, number) has a database read in that many ranges of a column at
    once; without it one task reads all of it.
    """
    if format == "table":
        return spark.table(uri)
    reader = spark.read.format(format).options(**options)
    if bounds is not None:
        reader = reader.options(**dict(zip(("partitionColumn", "lowerBound", "upperBound", "numPartitions"), map(str, bounds), strict=True)))
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load() if format == "jdbc" else reader.load(uri)


def strip_html(html):
    """Readable text of a page: scripts, styles, comments, tags and the commonest entities go."""
    text = html
    for pattern, by in ((r"(?is)<script.*?</script>", " "), (r"(?is)<style.*?</style>", " "), (r"(?s)<!--.*?-->", " "), (r"<[^>]*>", " "), ("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&"), (r"\s+", " ")):
        text = F.regexp_replace(text, pattern, by)
    return F.trim(text)


def load_texts(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """id, text of documents, pages (tags stripped), conversations or benchmark items."""
    df = spread(load_table(spark, sf_dir, kind))
    if kind == "pages":
        return df.select(F.col("page_id").alias("id"), strip_html(F.col("html")).alias("text"))
    if kind == "conversations":
        return df.select(F.concat_ws("-", "conv_id", "turn").alias("id"), "text")
    return df.select(F.col(df.columns[0]).alias("id"), "text")


def canonical(df: DataFrame) -> list:
    """Each column as text with its length before it, so that no two rows read alike; null is a dash.

    Nothing is rounded; negative zero is zero, and times have microseconds.
    """
    out = []
    for f in df.schema.fields:
        c = F.col(f"`{f.name}`")
        if isinstance(f.dataType, (T.DoubleType, T.FloatType)):
            c = c + F.lit(0.0).cast(f.dataType)
        elif isinstance(f.dataType, (T.TimestampType, T.TimestampNTZType)):
            c = F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")
        c = F.to_json(F.struct(c.alias("v"))) if isinstance(f.dataType, (T.ArrayType, T.MapType, T.StructType)) else F.base64(c) if isinstance(f.dataType, T.BinaryType) else c.cast("string")
        out.append(F.coalesce(F.concat(F.length(c).cast("string"), F.lit(":"), c), F.lit("-")))
    return out


def with_row_id(df: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """A key for each row: from its key columns, else a digest of the row, numbered where rows are equal."""
    if keys:
        return df.withColumn("row_id", F.concat_ws("-", *keys))
    marked = df.withColumn("row_id", F.md5(F.concat(*canonical(df))))
    # one scan and one exchange; rows of one digest are alike in all columns, so any of them may be the first
    turn = F.row_number().over(W.partitionBy("row_id").orderBy("row_id"))
    numbered = marked.withColumn("__n", turn)
    return numbered.withColumn("row_id", F.when(F.col("__n") == 1, F.col("row_id")).otherwise(F.concat_ws("-", "row_id", "__n"))).drop("__n")


# --- facts over time ---

#: Two event types are names of one concept.
ALIASES = {"purchase": "revenue", "signup": "revenue", "click": "clicks", "view": "views", "error": "errors", "refund": "refunds"}
CONCEPTS = ("revenue", "clicks", "views", "errors")


def facts_long(events: DataFrame) -> DataFrame:
    """entity, alias, value, period, filing_date, unit from the event stream."""
    return events.select(
        F.col("user_id").alias("entity"), F.col("event_type").alias("alias"), (F.col("value") + F.lit(0.0)).cast("decimal(24,6)").alias("value"),
        F.date_trunc("month", F.col("ts").cast("timestamp_ntz")).cast("date").alias("period"), F.col("ts").cast("date").alias("filing_date"), F.col("ts"),
        F.when(F.col("event_type").isin("purchase", "signup"), "usd").otherwise("count").alias("unit"),
    )


def canonical_concepts(facts: DataFrame, aliases: dict[str, str]) -> DataFrame:
    """Adds the canonical name of each alias; unknown ones keep their own."""
    pairs = [x for k, v in aliases.items() for x in (F.lit(k), F.lit(v))]
    return facts.withColumn("concept", F.coalesce(F.try_element_at(F.create_map(*pairs), F.col("alias")), F.col("alias")))


def latest_facts(facts: DataFrame, keys: list[str], order: str = "ts", fields: tuple[str, ...] = ("value", "period", "filing_date", "unit")) -> DataFrame:
    """The newest fact of each key: one aggregation, no window.  All fields are those of one fact; of facts of one
    time it is the greatest by its fields in turn, so the choice does not depend on the order of rows."""
    newest = F.max(F.when(F.col(order).isNotNull(), F.struct(order, *fields))).alias("__newest")
    return facts.groupBy(*keys).agg(newest).select(*keys, *(F.col(f"__newest.{c}").alias(c) for c in (*fields, order)))


def of_form(facts: DataFrame, forms: tuple[str, ...], column: str = "form") -> DataFrame:
    """Facts from filings of the given forms, such as the yearly and the quarterly one."""
    return facts.where(F.upper(F.trim(column)).isin(*(f.upper() for f in forms)))


def periodize(facts: DataFrame, kind: str) -> DataFrame:
    """Facts with the year, or the quarter, that they belong to."""
    year = F.year("period").cast("string")
    return facts.withColumn("span", year if kind == "year" else F.concat(year, F.lit("-Q"), F.quarter("period").cast("string")))


def facts_to_wide(facts: DataFrame, concepts: tuple[str, ...] = CONCEPTS, key: str = "entity", concept: str = "concept", order: str = "ts") -> DataFrame:
    """A row for each entity with value, period, filing date and unit of the newest fact of each concept.

    Conditional aggregates instead of a pivot after a group: one exchange.  Ties go as in ``latest_facts``.
    """
    fields = ("value", "period", "filing_date", "unit")
    newest = [F.max(F.when((F.col(concept) == c) & F.col(order).isNotNull(), F.struct(order, *fields))).alias(f"__{c}") for c in concepts]
    return facts.groupBy(key).agg(*newest).select(key, *(F.col(f"__{c}.{f}").alias(f"{c}_{f}") for c in concepts for f in fields))


def coalesce_aliases(wide: DataFrame, spec: dict[str, list[str]]) -> DataFrame:
    """Each target from the first of its aliases that is not null."""
    return wide.select("*", *(F.coalesce(*names).alias(target) for target, names in spec.items()))


def asof_facts(facts: DataFrame, at: DataFrame, keys: list[str], order: str = "ts", when: str = "at") -> DataFrame:
    """The newest fact not after each date asked for: a union and one window, no join by inequality."""
    asked = at.select(*keys, F.col(when).alias(order), F.lit(None).cast("decimal(24,6)").alias("value"), F.lit(1).alias("asked"))
    known = facts.select(*keys, order, "value", F.lit(0).alias("asked"))
    own = W.partitionBy(*keys).orderBy(order, "asked").rowsBetween(W.unboundedPreceding, 0)
    filled = known.union(asked).withColumn("value", F.last("value", ignorenulls=True).over(own))
    return filled.where("asked = 1").select(*keys, F.col(order).alias(when), "value")


def fact_history(facts: DataFrame, keys: list[str], days: int = 30, order: str = "ts") -> DataFrame:
    """Each fact among those of its key: the value before and after it, the first and the second, its quarter and
    place in time, and the sum of the given days up to it.  All frames share one exchange by key.
    """
    own = W.partitionBy(*keys).orderBy(order)
    whole = own.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    recent = W.partitionBy(*keys).orderBy(F.datediff(F.col(order).cast("date"), F.lit("1970-01-01").cast("date"))).rangeBetween(-days, 0)
    return facts.select(
        "*", F.lag("value").over(own).alias("previous"), F.lead("value").over(own).alias("following"), F.first_value("value").over(whole).alias("first"), F.nth_value("value", 2).over(whole).alias("second"),
        F.ntile(4).over(own).alias("quarter"), F.percent_rank().over(own).alias("place"), F.sum("value").over(recent).alias("recent"),
    )


# --- personal data, statistics, nulls ---

PII_NAMES = r"(?i)(^|_)(name|phone|email|address|contact)($|_)"
PII_VALUES = (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+\.[A-Za-z]{2,}", r"\+?[0-9]{2,3}[ -][0-9]{3}[ -][0-9]{3,4}", r"\b[0-9]{4}[ -][0-9]{4}[ -][0-9]{4}[ -][0-9]{4}\b")


def pii_columns(df: DataFrame, share: float = 0.2, exempt: tuple[str, ...] = ()) -> DataFrame:
    """column, by_name, hit_rate, flagged for each text column, in one pass over the values."""
    names = [f.name for f in df.schema.fields if isinstance(f.dataType, T.StringType)]
    rates = df.agg(*(F.avg(reduce(lambda a, b: a | b, (F.col(c).rlike(p) for p in PII_VALUES)).cast("double")).alias(c) for c in names)) if names else None
    if rates is None:
        return df.sparkSession.createDataFrame([], "column string, by_name boolean, hit_rate double, flagged boolean")
    long = rates.unpivot([], names, "column", "hit_rate")
    by_name = F.col("column").rlike(PII_NAMES)
    flagged = (by_name | (F.coalesce("hit_rate", F.lit(0.0)) >= share)) & ~F.col("column").isin(*exempt)
    return long.select("column", by_name.alias("by_name"), F.coalesce("hit_rate", F.lit(0.0)).alias("hit_rate"), flagged.alias("flagged"))


def drop_pii_columns(df: DataFrame, share: float = 0.2, exempt: tuple[str, ...] = ()) -> DataFrame:
    flagged = [r["column"] for r in pii_columns(df, share, exempt).where("flagged").collect()]  # a row a column
    return df.drop(*flagged)


def corpus_stats(tables: dict[str, DataFrame]) -> DataFrame:
    """table_name, n_rows, n_columns."""
    parts = [df.agg(F.count("*").alias("n_rows")).select(F.lit(n).alias("table_name"), "n_rows", F.lit(len(df.columns)).alias("n_columns")) for n, df in tables.items()]
    return reduce(DataFrame.union, parts)


def corpus_summary(stats: DataFrame) -> DataFrame:
    return stats.agg(F.count("*").alias("n_tables"), F.sum("n_rows").alias("n_rows"), F.avg("n_columns").alias("mean_columns"), F.avg("n_rows").alias("mean_rows"))


def inject_nulls(df: DataFrame, spec: dict[str, tuple[str, int]]) -> DataFrame:
    """Sets a column to null where its key column is a multiple of a number: {column: (key, n)}."""
    return df.withColumns({c: F.when(F.pmod(F.col(key), F.lit(n)) != 0, F.col(c)) for c, (key, n) in spec.items()})


# --- the tables that stand in for the paper's two domains ---


def order_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders, customer = load_table(spark, sf_dir, "orders"), load_table(spark, sf_dir, "customer")
    joined = orders.join(customer, orders.o_custkey == customer.c_custkey)
    return joined.select(
        F.col("o_orderkey").alias("order_key"), F.col("c_name").alias("customer"), F.col("c_mktsegment").alias("segment"), (F.col("o_totalprice") + F.lit(0.0)).cast("decimal(24,6)").alias("total_price"),
        F.col("o_orderdate").cast("date").alias("order_date"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), F.col("o_orderkey").cast("string").alias("row_id"),
    )


def order_facts_nulls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return inject_nulls(order_facts(spark, sf_dir), {"total_price": ("order_key", 7), "order_date": ("order_key", 11)})


def part_catalog(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "part").select(
        F.col("p_partkey").alias("part_key"), F.col("p_name").alias("part_name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").alias("size"),
        (F.col("p_retailprice") + F.lit(0.0)).cast("decimal(24,6)").alias("retail_price"), F.col("p_partkey").cast("string").alias("row_id"),
    )


def line_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    line, part = load_table(spark, sf_dir, "lineitem"), load_table(spark, sf_dir, "part")
    joined = with_row_id(line).join(part.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    d = lambda c: (F.col(c) + F.lit(0.0)).cast("decimal(24,6)")
    return joined.select(
        F.col("l_orderkey").alias("order_key"), F.col("l_partkey").alias("part_key"), d("l_quantity").alias("quantity"), d("l_extendedprice").alias("extended_price"), d("l_discount").alias("discount"),
        d("l_tax").alias("tax"), F.col("l_shipdate").cast("date").alias("ship_date"), F.col("p_brand").alias("brand"), "row_id",
    )


def company_facts_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    facts = canonical_concepts(facts_long(load_table(spark, sf_dir, "events")), ALIASES)
    return facts_to_wide(facts).withColumn("row_id", F.col("entity").cast("string"))


def customer_place(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n, r = (load_table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    joined = c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return joined.select(F.col("c_custkey").alias("customer_key"), F.col("c_name").alias("customer"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"), F.col("c_mktsegment").alias("segment"), (F.col("c_acctbal") + F.lit(0.0)).cast("decimal(24,6)").alias("balance"), F.col("c_custkey").cast("string").alias("row_id"))


def supplier_place(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, n, r = (load_table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    joined = s.join(n, s.s_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return joined.select(F.col("s_suppkey").alias("supplier_key"), F.col("s_name").alias("supplier"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"), (F.col("s_acctbal") + F.lit(0.0)).cast("decimal(24,6)").alias("balance"), F.col("s_suppkey").cast("string").alias("row_id"))


def brand_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many small tables in one: ``table_name`` is the brand."""
    return line_facts(spark, sf_dir).withColumn("table_name", F.lower(F.regexp_replace("brand", "#", "_")))
