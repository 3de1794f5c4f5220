"""Report plans: which columns of a table make one kind of report.

A profile is one aggregation over all columns.  Planning works on the profile and a few sample rows,
on the driver, once a table; what comes out is checked and can be stored as a table.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

COMPANIONS = ("period", "filing_date", "unit", "currency")
MOST, FEWEST, LARGEST = 5, 1, 8


@dataclass(frozen=True)
class PlanColumn:
    name: str
    role: str  # identifier, metric, attribute, temporal, companion
    metric: str | None = None  # what a companion belongs to
    companion: str | None = None


@dataclass(frozen=True)
class ReportType:
    name: str
    columns: tuple[PlanColumn, ...]

    def names(self) -> list[str]:
        return [c.name for c in self.columns]


@dataclass(frozen=True)
class Plan:
    table: str
    types: tuple[ReportType, ...] = field(default_factory=tuple)


class InvalidPlan(ValueError):
    pass


def sample_rows(df: DataFrame, n: int = 10, method: str = "hash", key: str = "row_id", strata: str | None = None, seed: str = "") -> DataFrame:
    """``hash``: the n rows with the least digest of their key; ``head``: any n; ``stratified``: spread over a column."""
    if method == "head":
        return df.limit(n)
    code = F.md5(F.concat_ws("|", F.lit(seed), F.col(key).cast("string"))) if seed else F.md5(F.col(key).cast("string"))
    if method == "hash":
        return df.orderBy(code, key).limit(n)
    turn = F.row_number().over(W.partitionBy(strata).orderBy(code, key))
    return df.withColumn("__turn", turn).where(F.col("__turn") <= n).orderBy("__turn", code, key).limit(n).drop("__turn")


def sample_fraction(df: DataFrame, fractions: dict[str, float], strata: str, key: str = "row_id", seed: str = "") -> DataFrame:
    """Of each stratum its share, chosen by a digest of the key, so the same rows however the table is cut.

    A stratum that is not named has none.
    """
    share = F.coalesce(*(F.when(F.col(strata) == s, F.lit(float(x))) for s, x in fractions.items()), F.lit(0.0))
    place = F.conv(F.substring(F.md5(F.concat(F.lit(seed), F.col(key).cast("string"))), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))
    return df.where(place < share)


def profile_top(df: DataFrame, columns: list[str], k: int = 10) -> DataFrame:
    """column, value, n, rank of the k commonest values, equal counts in order of value: counted in tasks before the
    exchange, and each task keeps no more than k values a column for the ranking."""
    cells = F.array(*(F.struct(F.lit(c).alias("column"), F.col(f"`{c}`").cast("string").alias("value")) for c in columns))
    long = df.select(F.inline(cells)).where("value is not null")
    counts = long.groupBy("column", "value").agg(F.count("*").alias("n"))
    turn = F.row_number().over(W.partitionBy("column").orderBy(F.desc("n"), "value"))
    return counts.withColumn("rank", turn).where(F.col("rank") <= k)


def kind_of(f: T.StructField) -> str:
    if isinstance(f.dataType, (T.DateType, T.TimestampType, T.TimestampNTZType)):
        return "temporal"
    return "numeric" if isinstance(f.dataType, T.NumericType) else "text"


def profile_columns(df: DataFrame, table: str, exact: bool = False) -> DataFrame:
    """A row for each column, all from one pass: type, kind, counts, range, mean, mean length."""
    distinct = F.count_distinct if exact else F.approx_count_distinct
    fields = [f for f in df.schema.fields if f.name != "row_id"]
    made = []
    for f in fields:
        c, number = F.col(f"`{f.name}`"), kind_of(f) == "numeric"
        text = c.cast("string") if not number else c.cast("decimal(24,6)").cast("string")
        made.append(F.struct(
            F.lit(f.name).alias("column"), F.lit(f.dataType.simpleString()).alias("dtype"), F.lit(kind_of(f)).alias("base"), F.count(F.lit(1)).alias("n"), F.count_if(c.isNull()).alias("n_null"), distinct(c).alias("n_distinct"),
            F.min(c.cast("decimal(24,6)") if number else text).cast("string").alias("min"), F.max(c.cast("decimal(24,6)") if number else text).cast("string").alias("max"),
            (F.avg(c.cast("decimal(24,6)")).cast("double") if number else F.lit(None).cast("double")).alias("mean"), F.avg(F.length(text)).alias("avg_len"),
        ))
    wide = df.agg(*(m.alias(f"c{i}") for i, m in enumerate(made)))
    long = wide.select(F.inline(F.array(*(f"c{i}" for i in range(len(made))))))
    identifier = F.col("column").rlike(r"(?i)(^|_)(key|id|ticker|code|entity)$") | ((F.col("base") == "text") & (F.col("n_distinct") >= 0.95 * F.col("n")))
    kind = F.when(F.col("base") == "temporal", "temporal").when(identifier, "identifier").when(F.col("base") == "numeric", "numeric").when(F.col("avg_len") > 40, "text").otherwise("categorical")
    return long.select(F.lit(table).alias("table_name"), "column", "dtype", kind.alias("kind"), "n", "n_null", "n_distinct", "min", "max", "mean", "avg_len")


def profile_sketches(df: DataFrame, columns: list[str]) -> DataFrame:
    """Mergeable profile for very large tables: distinct counts and quartiles of bounded state, by column."""
    made = [F.struct(F.lit(c).alias("column"), F.hll_sketch_estimate(F.hll_sketch_agg(F.col(c).cast("string"))).alias("n_distinct"), F.approx_percentile(F.col(c).cast("double"), [0.25, 0.5, 0.75]).alias("quartiles")) for c in columns]
    return df.agg(*(m.alias(c) for m, c in zip(made, columns, strict=True))).select(F.inline(F.array(*columns)))


# --- planner ---


def _stem(name: str) -> str:
    for c in COMPANIONS:
        if name.endswith("_" + c):
            return name[: -len(c) - 1]
    return name[:-6] if name.endswith("_value") else name


def _band(row: dict) -> str:
    """Money-like, ratio-like or count-like."""
    name, low, high = row["column"], float(row["min"] or 0), float(row["max"] or 0)
    if 0 <= low and high <= 1 and any(x in name for x in ("discount", "tax", "rate", "share", "ratio")):
        return "rates"
    if any(x in name for x in ("price", "balance", "revenue", "cost", "amount", "value")):
        return "amounts"
    return "counts"


def rule_plan(table: str, profile: list[dict], mode: str = "grouped") -> Plan:
    """Groups by companions and magnitude; ``single_type`` and ``enumerate`` are baselines without planning."""
    order = [r["column"] for r in profile]
    kinds = {r["column"]: r["kind"] for r in profile}
    identifiers = [c for c in order if kinds[c] == "identifier"]
    companion_of: dict[str, list[str]] = {}
    metrics, attributes, temporal = [], [], []
    stems = {_stem(c): c for c in order if kinds[c] == "numeric"}
    for c in order:
        if c in identifiers:
            continue
        stem = _stem(c)
        if stem != c and stem in stems and stems[stem] != c:
            companion_of.setdefault(stems[stem], []).append(c)
        elif kinds[c] == "numeric":
            metrics.append(c)
        elif kinds[c] == "temporal":
            temporal.append(c)
        else:
            attributes.append(c)

    def type_of(name: str, members: list[str]) -> ReportType:
        columns = [PlanColumn(c, "identifier") for c in identifiers]
        for m in members:
            role = "metric" if m in metrics else "temporal" if m in temporal else "attribute"
            columns.append(PlanColumn(m, role))
            columns += [PlanColumn(c, "companion", m, next(x for x in COMPANIONS if c.endswith(x))) for c in companion_of.get(m, [])]
        if not any(c.companion for c in columns) and temporal and not any(c.role == "temporal" for c in columns) and any(c.role == "metric" for c in columns):
            columns.append(PlanColumn(temporal[0], "temporal"))
        return ReportType(name, tuple(columns))

    if mode == "single_type":
        return Plan(table, (type_of("all", metrics + attributes + temporal),))
    if mode == "enumerate":
        return Plan(table, tuple(type_of(c, [c]) for c in metrics + attributes + temporal))
    rows = {r["column"]: r for r in profile}
    groups: dict[str, list[str]] = {}
    for m in metrics:
        groups.setdefault(_band(rows[m]), []).append(m)
    if attributes:
        groups["description"] = attributes
    if not groups and temporal:
        groups["dates"] = list(temporal)
    if not groups:
        groups["identity"] = []
    small = sorted((g for g in groups if len(groups[g]) < 2 and g != "description"), key=lambda g: order.index(groups[g][0]) if groups[g] else 0)
    numeric = [g for g in groups if g != "description"]
    for g in small:  # lone metrics join the nearest group of metrics
        others = [x for x in numeric if x != g and x in groups]
        if others:
            groups[others[0]] = sorted(groups[others[0]] + groups.pop(g), key=order.index)

    def types(most: int) -> list[ReportType]:
        """Groups in parts of one size, the least that leaves at most ``most`` parts."""
        size = LARGEST
        while sum(max(1, -(-len(x) // size)) for x in groups.values()) > most:
            size += 1
        out = []
        for g, members in groups.items():
            parts = [members[i : i + size] for i in range(0, len(members), size)] or [[]]
            out += [type_of(g if len(parts) == 1 else f"{g}_{i + 1}", p) for i, p in enumerate(parts)]
        return out

    def without(found: list[ReportType]) -> list[str]:
        return [c for c in temporal if not any(c in t.names() for t in found)]

    found = types(MOST)
    if without(found) and len(found) == MOST:
        found = types(MOST - 1)
    if dates := without(found):  # dates that no report of metrics has
        found.append(type_of("dates", dates))
    return Plan(table, tuple(found))


def plan_reports(profile: DataFrame, sample: DataFrame | None = None, backend=None, mode: str = "grouped") -> Plan:
    """One call a table: of a model, or of the rules above.  A profile has a row a column."""
    rows = [r.asDict() for r in profile.collect()]
    table = rows[0]["table_name"]
    if backend is None:
        return rule_plan(table, rows, mode)
    shown = [{k: None if v is None else str(v) for k, v in r.asDict().items()} for r in (sample.limit(10).collect() if sample is not None else [])]
    answer = backend.plan({"table": table, "columns": [{k: r[k] for k in ("column", "dtype", "kind")} for r in rows], "rows": shown, "max_types": MOST})
    return Plan(table, tuple(ReportType(t["report_type"], tuple(PlanColumn(c, "attribute") for c in t["columns"])) for t in answer))


def validate_plan(plan: Plan, columns: list[str], lo: int = FEWEST, hi: int = MOST, allow_reuse: bool = True) -> Plan:
    """The plan itself, or ``InvalidPlan``."""
    if not lo <= len(plan.types) <= hi:
        raise InvalidPlan(f"{len(plan.types)} report types; {lo} to {hi} are allowed")
    seen, names, used = set(), set(), set()
    for t in plan.types:
        own = frozenset(t.names())
        if unknown := own - set(columns):
            raise InvalidPlan(f"{t.name}: no such columns: {sorted(unknown)}")
        if own in seen or t.name in names:
            raise InvalidPlan(f"{t.name}: the same set of columns, or name, twice")
        free = {c.name for c in t.columns if c.role != "identifier"}
        if not allow_reuse and used & free:
            raise InvalidPlan(f"{t.name}: columns used before: {sorted(used & free)}")
        used |= free
        seen.add(own)
        names.add(t.name)
    return plan


def ensure_identifiers(plan: Plan, identifiers: list[str]) -> Plan:
    """Identifiers of the table come first in every type."""
    def complete(t: ReportType) -> ReportType:
        own = {c.name for c in t.columns}
        return ReportType(t.name, tuple(PlanColumn(i, "identifier") for i in identifiers if i not in own) + t.columns)

    return Plan(plan.table, tuple(complete(t) for t in plan.types))


def plan_table(spark: SparkSession, plan: Plan) -> DataFrame:
    rows = [(plan.table, t.name, i + 1, j + 1, c.name, c.role, c.metric, c.companion) for i, t in enumerate(plan.types) for j, c in enumerate(t.columns)]
    return spark.createDataFrame(rows, "table_name string, report_type string, ordinal int, position int, column string, role string, metric string, companion string")


def similarity_of_plans(a: Plan, b: Plan) -> float:
    """Mean over the types of a of the best Jaccard of column sets in b."""
    score = lambda x, y: len(x & y) / len(x | y) if x | y else 1.0
    sets = [[frozenset(t.names()) for t in p.types] for p in (a, b)]
    return sum(max(score(x, y) for y in sets[1]) for x in sets[0]) / len(sets[0])


def plan_stability(df: DataFrame, table: str, sizes: tuple[int, ...] = (5, 10, 20, 50)) -> DataFrame:
    """How alike the plans from samples of different sizes are, by pairs of sizes."""
    plans = {n: plan_reports(profile_columns(sample_rows(df, n), table, exact=True)) for n in sizes}
    rows = [(table, a, b, float(similarity_of_plans(plans[a], plans[b]))) for a, b in combinations(sizes, 2)]
    return df.sparkSession.createDataFrame(rows, "table_name string, size_a int, size_b int, similarity double")


# --- declared plans of the given tables ---


def declared(table: str, name: str, identifiers: str, members: str) -> ReportType:
    """Members: a word each; ``m+period,filing_date`` is a metric with companions."""
    columns = [PlanColumn(c, "identifier") for c in identifiers.split()]
    for word in members.split():
        m, _, companions = word.partition("+")
        metric = f"{m}_value" if companions else m
        role = "temporal" if m.endswith("_date") else "attribute" if m in ("status", "priority", "segment", "brand", "type", "nation", "region") else "metric"
        columns.append(PlanColumn(metric, role))
        columns += [PlanColumn(f"{m}_{c}", "companion", metric, c) for c in companions.split(",") if c]
    return ReportType(name, tuple(columns))


def _plans() -> dict[str, Plan]:
    full = "+period,filing_date,unit"
    return {
        "order_facts": Plan("order_facts", (declared("order_facts", "order_value", "order_key customer", "total_price order_date"), declared("order_facts", "order_handling", "order_key customer", "status priority segment order_date"))),
        "part_catalog": Plan("part_catalog", (declared("part_catalog", "pricing", "part_key part_name", "retail_price size"), declared("part_catalog", "description", "part_key part_name", "brand type"))),
        "company_facts_wide": Plan("company_facts_wide", (declared("company_facts_wide", "earning", "entity", f"revenue{full} clicks{full}"), declared("company_facts_wide", "activity", "entity", f"views{full} errors{full}"))),
        "line_facts": Plan("line_facts", (declared("line_facts", "shipment", "order_key part_key", "quantity extended_price discount tax ship_date"),)),
        "customer_place": Plan("customer_place", (declared("customer_place", "place", "customer_key customer", "nation region segment"), declared("customer_place", "account", "customer_key customer", "balance"))),
        "supplier_place": Plan("supplier_place", (declared("supplier_place", "account", "supplier_key supplier", "nation region balance"),)),
    }


DECLARED = _plans()
