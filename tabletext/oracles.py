"""The library's queries as SQL for DuckDB, written apart from the Spark code, and the literal fixtures of both."""

from __future__ import annotations

from .functions import numeric, temporal
from .operators.validation import METRICS
from .plans.planning import DECLARED, Plan
from .sources.tables import ALIASES, CONCEPTS, PII_NAMES, PII_VALUES, TABLES

# --- fixtures ---

#: truth, found: edges of the tolerance
EDGES = (("1000", "1000.9"), ("1000", "1001"), ("1000", "1001.1"), ("1000", "999"), ("1000", "998.9"), ("0", "0"), ("0", "0.0001"), ("-50", "-50.05"), ("-50", "50"))
SURFACES = ("$1,234.50", "(1,234.50)", "-$12.00", "2.65595E+11", "5.00%", "12 percent", "3.2 million", "$1.5 billion", "7", "$2 thousand")
TRAP = (("a", "x", 0.9), ("a", "y", 0.8), ("b", "x", 0.8), ("b", "y", 0.1))


def _text(x) -> str:
    return "null" if x is None else "'" + str(x).replace("'", "''") + "'"


def _rows(rows, names: str) -> str:
    return "(values " + ", ".join("(" + ", ".join(_text(x) if isinstance(x, str) or x is None else str(x) for x in r) + ")" for r in rows) + f") as v({names})"


# --- sources ---

D = "decimal(24,6)"
R = "decimal(18,6)"
ORDER_FACTS = f"""select o_orderkey as order_key, c_name as customer, c_mktsegment as segment, cast(o_totalprice + 0.0 as {D}) as total_price, cast(o_orderdate as date) as order_date,
 o_orderstatus as status, o_orderpriority as priority, cast(o_orderkey as varchar) as row_id from orders join customer on o_custkey = c_custkey"""
ORDER_NULLS = f"select * replace (case when order_key % 7 <> 0 then total_price end as total_price, case when order_key % 11 <> 0 then order_date end as order_date) from ({ORDER_FACTS})"
PART_CATALOG = f"select p_partkey as part_key, p_name as part_name, p_brand as brand, p_type as type, p_size as size, cast(p_retailprice + 0.0 as {D}) as retail_price, cast(p_partkey as varchar) as row_id from part"
_LINE = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus")
_LINE_ID = "md5(" + " || ".join(f"length(cast({c} as varchar)) || ':' || cast({c} as varchar)" for c in _LINE) + " || '26:' || strftime(l_shipdate, '%Y-%m-%d %H:%M:%S.%f'))"
LINE_IDS = f"select *, case when row_number() over (partition by digest) = 1 then digest else digest || '-' || row_number() over (partition by digest) end as row_id from (select *, {_LINE_ID} as digest from lineitem)"
LINE_FACTS = f"""select l_orderkey as order_key, l_partkey as part_key, cast(l_quantity + 0.0 as {D}) as quantity, cast(l_extendedprice + 0.0 as {D}) as extended_price, cast(l_discount + 0.0 as {D}) as discount,
 cast(l_tax + 0.0 as {D}) as tax, cast(l_shipdate as date) as ship_date, p_brand as brand, row_id from ({LINE_IDS}) join part on l_partkey = p_partkey"""
FACTS = f"""select user_id as entity, event_type as alias, cast(value + 0.0 as {D}) as value, cast(date_trunc('month', ts) as date) as period, cast(ts as date) as filing_date, ts,
 case when event_type in ('purchase', 'signup') then 'usd' else 'count' end as unit from events"""
CONCEPT = "case alias " + " ".join(f"when '{a}' then '{c}'" for a, c in ALIASES.items()) + " else alias end"
COMPANY = (
    f"select entity, " + ", ".join(f"arg_max({f}, ts) filter (where concept = '{c}') as {c}_{f}" for c in CONCEPTS for f in ("value", "period", "filing_date", "unit"))
    + f", cast(entity as varchar) as row_id from (select *, {CONCEPT} as concept from ({FACTS})) group by entity"
)

# --- text of reports ---

_KINDS = {"total_price": "money", "retail_price": "money", "extended_price": "money", "revenue_value": "money", "discount": "ratio", "tax": "ratio", "quantity": "quantity", "clicks_value": "quantity", "views_value": "quantity", "errors_value": "quantity"}
LONG = "%B %-d, %Y"


def surface(c: str) -> str:
    kind = _KINDS.get(c)
    if kind == "ratio":
        return f"(format('{{:,.2f}}', cast({c} * 100 as double)) || '%')"
    if kind:
        return f"(case when {c} < 0 then '-' else '' end || '{'$' if kind == 'money' else ''}' || format('{{:,.2f}}', abs(cast({c} as double))))"
    if c.endswith(("_date", "_period")):
        return f"strftime({c}, '{LONG}')"
    return f"cast({c} as varchar)"


def _label(c: str) -> str:
    return c.removesuffix("_value").replace("_", " ")


def _verb(c: str, fixed: bool) -> str:
    if fixed:
        return "'is'"
    return f"list_extract(['is', 'was recorded as', 'stands at', 'came to'], cast(cast('0x' || substr(md5(row_id || '|{c}'), 1, 2) as integer) % 4 + 1 as integer))"


def text_of(kind, fixed: bool = False) -> str:
    """The passage of a report type as an expression."""
    opening = "'This report covers ' || concat_ws(' and ', " + ", ".join(f"'{_label(c.name)} ' || {surface(c.name)}" for c in kind.columns if c.role == "identifier") + ") || '.'"
    words = {"period": " for the period ending ", "filing_date": ", filed on ", "unit": ", stated in "}
    out = [opening]
    for c in kind.columns:
        if c.role in ("identifier", "companion"):
            continue
        more = "".join(f" || coalesce('{words[x.companion]}' || {surface(x.name)}, '')" for x in kind.columns if x.role == "companion" and x.metric == c.name)
        out.append(f"'Its {_label(c.name)} ' || {_verb(c.name, fixed)} || ' ' || {surface(c.name)}{more} || '.'")
    return "concat_ws(' ', " + ", ".join(out) + ")"


def reports(source: str, plan: Plan, fixed: bool = False) -> str:
    return " union all ".join(f"select '{t.name}' as report_type, row_id, {text_of(t, fixed)} as text from ({source})" for t in plan.types)


ORDERS = DECLARED["order_facts"]
VALUE_TYPE = ORDERS.types[0]
#: The order reports with what is done to them, and the counts that follow from that.
DAMAGED = f"""select *, case when code = 3 then 'stray_year' when report_type <> 'order_value' then 'none' when code = 0 then 'drop' when code = 1 then 'beyond' when code = 2 then 'within' else 'none' end as damage
 from (select report_type, row_id, text, cast(row_id as bigint) % 5 as code from ({reports(ORDER_FACTS, ORDERS)}))"""
_N_TRUTH = "case when report_type = 'order_value' then 2 else 1 end"
COUNTS = f"""select *, n_truth - n_tp as n_fn, case when damage = 'beyond' then 1 else 0 end as n_fp, 1 as t_tp, 0 as t_fn, case when damage = 'stray_year' then 1 else 0 end as t_fp
 from (select *, {_N_TRUTH} as n_truth, case when damage in ('drop', 'beyond') then 1 else {_N_TRUTH} end as n_tp from ({DAMAGED}))"""
SCORED = """select 'order_facts' as dataset, *, n_tp / (n_tp + n_fp) as numeric_p, n_tp / (n_tp + n_fn) as numeric_r, 2 * n_tp / (2 * n_tp + n_fp + n_fn) as numeric_f1,
 t_tp / (t_tp + t_fp) as temporal_p, t_tp / (t_tp + t_fn) as temporal_r, 2 * t_tp / (2 * t_tp + t_fp + t_fn) as temporal_f1 from (""" + COUNTS + ")"


def _prf(tp: str, fp: str, fn: str) -> str:
    return f"{tp} as tp, {fp} as fp, {fn} as fn, cast({tp} / nullif({tp} + {fp}, 0) as {R}) as p, cast({tp} / nullif({tp} + {fn}, 0) as {R}) as r, cast(2 * {tp} / nullif(2 * {tp} + {fp} + {fn}, 0) as {R}) as f1"


# --- parsers ---


def _q(pattern: str) -> str:
    return _text(pattern)


MONTHS = "'janfebmaraprmayjunjulaugsepoctnovdec'"


def _month(s: str) -> str:
    return f"lpad(cast((instr({MONTHS}, lower(substr({s}, 1, 3))) + 2) // 3 as varchar), 2, '0')"


def date_value(s: str) -> str:
    """The normal form of a surface, case by case."""
    m = temporal.MONTH
    x = lambda pattern, i=1: f"regexp_extract({s}, {_q(pattern)}, {i})"
    two = lambda v: f"lpad({v}, 2, '0')"
    us, long, first = r"^(\d{1,2})/(\d{1,2})/(\d{2,4})$", rf"^({m}) (\d{{1,2}}), (\d{{4}})$", rf"^(\d{{1,2}}) ({m}) (\d{{4}})$"
    return (
        f"case when regexp_matches({s}, {_q(r'^\d{4}-\d{2}-\d{2}$')}) then {s}"
        f" when regexp_matches({s}, {_q(us)}) then case when length({x(us, 3)}) = 2 then '20' || {x(us, 3)} else {x(us, 3)} end || '-' || {two(x(us, 1))} || '-' || {two(x(us, 2))}"
        f" when regexp_matches({s}, {_q(long)}) then {x(long, 3)} || '-' || {_month(x(long, 1))} || '-' || {two(x(long, 2))}"
        f" when regexp_matches({s}, {_q(first)}) then {x(first, 3)} || '-' || {_month(x(first, 2))} || '-' || {two(x(first, 1))}"
        f" when {s} like '% quarter of %' then right({s}, 4) || '-Q' || case when {s} like 'f%r%t %' and {s} like 'first%' or {s} like '1%' then 1 when {s} like 's%' or {s} like '2%' then 2 when {s} like 't%' or {s} like '3%' then 3 else 4 end"
        f" when regexp_matches({s}, {_q(r'^\d{4} Q[1-4]$')}) then substr({s}, 1, 4) || '-' || right({s}, 2)"
        f" when regexp_matches({s}, {_q(r'^Q[1-4] \d{4}$')}) then right({s}, 4) || '-' || substr({s}, 1, 2)"
        f" when regexp_matches({s}, {_q(rf'^{m} \d{{4}}$')}) then right({s}, 4) || '-' || {_month(s)}"
        f" else right({s}, 4) end"
    )


def dates_in(text: str) -> str:
    return f"list_transform(regexp_extract_all({text}, {_q(temporal.PATTERN)}), lambda s: {date_value('s')})"


def masked(text: str) -> str:
    return f"regexp_replace(regexp_replace({text}, {_q(temporal.PATTERN)}, ' ', 'g'), {_q(numeric.IDENTIFIERS)}, ' ', 'g')"


def surfaces_in(text: str) -> str:
    return f"regexp_extract_all({masked(text)}, {_q(numeric.PATTERN)})"


def number_value(s: str) -> str:
    digits = rf"{numeric._DIGITS}(?:[eE][+-]?[0-9]+)?"
    plain = f"cast(replace(regexp_extract({s}, {_q(digits)}), ',', '') as {D})"
    scale = f"case when {s} like '%thousand' then 1000 when {s} like '%million' then 1000000 when {s} like '%billion' then 1000000000 when {s} like '%trillion' then 1000000000000 else 1 end"
    return f"cast(cast({plain} * case when {s} like '(%' or {s} like '-%' then -1 else 1 end as decimal(38,6)) * {scale} / case when {s} like '%\\%%' escape '\\' or {s} like '%percent%' then 100 else 1 end as {D})"


def number_unit(s: str) -> str:
    return f"case when {s} like '%\\%%' escape '\\' or {s} like '%percent%' then 'percent' when {s} like '%$%' then 'usd' else 'count' end"


def strip_html(c: str) -> str:
    for pattern, by in ((r"(?is)<script.*?</script>", " "), (r"(?is)<style.*?</style>", " "), (r"(?s)<!--.*?-->", " "), (r"<[^>]*>", " "), ("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&"), (r"\s+", " ")):
        c = f"regexp_replace({c}, {_q(pattern)}, {_q(by)}, 'g')"
    return f"trim({c})"


def _profile(source: str, table: str, columns: list[tuple[str, str, str]]) -> str:
    """column, Spark type, base kind"""
    out = []
    for c, dtype, base in columns:
        number = base == "numeric"
        text = f"cast(cast({c} as {D}) as varchar)" if number else f"cast({c} as varchar)"
        value = f"cast({c} as {D})" if number else text
        identifier = f"regexp_matches('{c}', '(?i)(^|_)(key|id|ticker|code|entity)$') or ('{base}' = 'text' and count(distinct {c}) >= 0.95 * count(*))"
        out.append(
            f"select '{table}' as table_name, '{c}' as \"column\", '{dtype}' as dtype, case when '{base}' = 'temporal' then 'temporal' when {identifier} then 'identifier' when '{base}' = 'numeric' then 'numeric' when avg(length({text})) > 40 then 'text' else 'categorical' end as kind,"
            f" count(*) as n, count(*) - count({c}) as n_null, count(distinct {c}) as n_distinct, cast(min({value}) as varchar) as min, cast(max({value}) as varchar) as max,"
            f" {f'cast(avg(cast({c} as {D})) as {R})' if number else f'cast(null as {R})'} as mean, cast(avg(length({text})) as {R}) as avg_len from ({source})"
        )
    return " union all ".join(out)


def _sweep(score: str, with_all: bool = True) -> str:
    taus = ["1.00", "0.95", "0.90", "0.85", "0.80", "0.75", "0.70"] + (["0.00"] if with_all else [])
    m = ", ".join(f"cast(avg({c}) as {R}) as avg_{c}" for c in ("numeric_p", "numeric_r", "temporal_p", "temporal_r"))
    return " union all ".join(
        f"select 'order_facts' as dataset, cast({t} as decimal(3,2)) as tau, count(*) as n_reports, cast(count(*) / (select count(*) from s) as {R}) as retained_share, {m} from s where {score} >= {t}" for t in taus
    )


#: claims, contradicted and ungrounded claims of the damaged order reports
CLAIMS = """select *, case report_type when 'order_value' then 3 else 5 end + case damage when 'stray_year' then 1 when 'drop' then -1 else 0 end as n_claims,
 case when damage = 'beyond' then 1 else 0 end as n_contradicted, case when damage in ('beyond', 'stray_year') then 1 else 0 end as n_ungrounded from (""" + DAMAGED + ")"


def _level(share: str) -> str:
    return f"case when {share} >= 1 then 5 when {share} >= 0.9 then 4 when {share} >= 0.7 then 3 when {share} >= 0.4 then 2 else 1 end"


JUDGED = f"""select *, (f + h + c) / 3 as overall, abs(least(f, h) - {_level('1 - n_ungrounded / n_claims')}) <= 1 as consistent from
 (select *, {_level('1 - n_contradicted / n_claims')} as f, {_level('1 - n_ungrounded / n_claims')} as h, 5 as c from ({CLAIMS}))"""


def _plan_rows(rows: list[tuple], names: str) -> str:
    return f"select * from {_rows(rows, names)}"


def _sentence_share() -> str:
    own = r"list_filter(string_split(regexp_replace(text, '[.!?\n] *', '.' || chr(10), 'g'), chr(10)), lambda s: length(s) > 1)"
    return f"select doc_id, quality, case when len(list_distinct(s)) * 10 >= len(s) * 9 then 1 else 0 end as rule from (select doc_id, {own} as s from documents) join labels using (doc_id)"


def build() -> dict[str, str]:
    out: dict[str, str] = {}
    full = [f"{c}_{f}" for c in CONCEPTS for f in ("value", "period", "filing_date", "unit")]
    out["facts_latest"] = f"select entity, alias, arg_max(value, ts) as value, arg_max(period, ts) as period, arg_max(filing_date, ts) as filing_date, arg_max(unit, ts) as unit from ({FACTS}) group by entity, alias"
    out["facts_wide"] = f"select entity, {', '.join(full)} from ({COMPANY})"
    out["facts_alias_coalesce"] = f"select entity, signup, purchase, coalesce(signup, purchase) as revenue from (select entity, arg_max(value, ts) filter (where alias = 'signup') as signup, arg_max(value, ts) filter (where alias = 'purchase') as purchase from ({FACTS}) where alias <> 'signup' or entity % 3 <> 0 group by entity)"
    spans = [("year", "cast(year(period) as varchar)"), ("quarter", "year(period) || '-Q' || quarter(period)")]
    out["facts_periodized"] = " union all ".join(f"select concept, {e} as span, count(*) as n, cast(sum(value) as {D}) as total from (select *, {CONCEPT} as concept from ({FACTS})) group by 1, 2" for _, e in spans)
    hit = lambda c: " or ".join(f"regexp_matches({c}, {_q(p)})" for p in PII_VALUES)
    pii = [("customer", c) for c in ("c_name", "c_mktsegment")] + [("documents", c) for c in ("text", "lang", "source")] + [("conversations", c) for c in ("role", "text")]
    out["pii_columns_flagged"] = " union all ".join(f"select '{t}' as table_name, '{c}' as \"column\", regexp_matches('{c}', {_q(PII_NAMES)}) as by_name, cast(avg(case when {hit(c)} then 1.0 else 0.0 end) as {R}) as hit_rate, regexp_matches('{c}', {_q(PII_NAMES)}) or avg(case when {hit(c)} then 1.0 else 0.0 end) >= 0.2 as flagged from {t}" for t, c in pii)
    widths = {"region": 2, "nation": 3, "customer": 5, "supplier": 4, "part": 6, "orders": 6, "lineitem": 11, "events": 6}
    out["corpus_stats"] = " union all ".join(f"select '{t}' as table_name, count(*) as n_rows, {widths[t]} as n_columns from {t}" for t in TABLES)
    out["benchmark_summary"] = f"select count(*) as n_tables, sum(n_rows) as n_rows, cast(avg(n_columns) as {R}) as mean_columns, cast(avg(n_rows) as {R}) as mean_rows from ({out['corpus_stats']})"
    out["small_tables"] = f"select lower(replace(brand, '#', '_')) as table_name, count(*) as n_rows, 8 as n_columns from ({LINE_FACTS}) group by 1"
    out["row_id_lineitem"] = f"select l_orderkey, l_linenumber, row_id from ({LINE_IDS})"
    out["asof_fact"] = f"select e.entity, f.value from (select distinct entity from ({FACTS})) e left join (select entity, arg_max(value, ts) as value from ({FACTS}) where ts <= timestamp '2024-01-15' group by entity) f using (entity)"

    out["sample_ten_orders"] = f"select row_id, customer, total_price, order_date from ({ORDER_FACTS}) order by md5(row_id), row_id limit 10"
    out["profile_part"] = _profile(PART_CATALOG, "part_catalog", [("part_key", "bigint", "numeric"), ("part_name", "string", "text"), ("brand", "string", "text"), ("type", "string", "text"), ("size", "int", "numeric"), ("retail_price", "decimal(24,6)", "numeric")])
    out["profile_orders"] = _profile(ORDER_FACTS, "order_facts", [("order_key", "bigint", "numeric"), ("customer", "string", "text"), ("segment", "string", "text"), ("total_price", "decimal(24,6)", "numeric"), ("order_date", "date", "temporal"), ("status", "string", "text"), ("priority", "string", "text")])
    names = 'report_type, position, "column", role'
    out["plan_orders"] = _plan_rows([("amounts", 1, "order_key", "identifier"), ("amounts", 2, "customer", "identifier"), ("amounts", 3, "total_price", "metric"), ("amounts", 4, "order_date", "temporal"), ("description", 1, "order_key", "identifier"), ("description", 2, "customer", "identifier"), ("description", 3, "segment", "attribute"), ("description", 4, "status", "attribute"), ("description", 5, "priority", "attribute")], names)
    members = [("amounts", i + 2, f"{c}_{f}", "metric" if f == "value" else "companion", None if f == "value" else f"{c}_value", None if f == "value" else f) for i, (c, f) in enumerate((c, f) for c in CONCEPTS for f in ("value", "period", "filing_date", "unit"))]
    out["plan_events_wide"] = _plan_rows([("amounts", 1, "entity", "identifier", None, None), *members], f"{names}, metric, companion")
    single = [("part_key", "identifier"), ("size", "metric"), ("retail_price", "metric"), ("part_name", "attribute"), ("brand", "attribute"), ("type", "attribute")]

    for key, source, plan in (("reports_orders", ORDER_FACTS, ORDERS), ("reports_nulls", ORDER_NULLS, ORDERS), ("reports_part", PART_CATALOG, DECLARED["part_catalog"]), ("reports_events", COMPANY, DECLARED["company_facts_wide"])):
        out[key] = f"select report_type, row_id, text from ({reports(source, plan)})"
    out["reports_template"] = f"select report_type, row_id, text from ({reports(PART_CATALOG, DECLARED['part_catalog'], fixed=True)})"
    out["reports_lines"] = f"select row_id, {text_of(DECLARED['line_facts'].types[0])} as text from ({LINE_FACTS})"
    price = surface("total_price")
    altered = lambda by: f"replace(text, ' ' || {price}, ' $' || format('{{:,.2f}}', cast(cast(floor(({by}) * 100 + 0.5) as decimal(20,0)) / 100 as double)))"
    out["reports_corrupted"] = f"""select report_type, row_id, damage, case damage when 'stray_year' then text || ' These figures close the fiscal year 2024.'
 when 'drop' then regexp_replace(text, ' Its total price [^$]*\\$[0-9,]+\\.[0-9][0-9]\\.', '')
 when 'beyond' then {altered('total_price * 1.01 + 1')} when 'within' then {altered('total_price * 1.0005')} else text end as text
 from ({DAMAGED}) join (select row_id, total_price from ({ORDER_FACTS})) using (row_id)"""
    none = f"cast(null as {D})"
    cells = [("pricing", "part_key", "integer", f"cast(part_key as {D})"), ("pricing", "part_name", "text", none), ("pricing", "retail_price", "money", "retail_price"), ("pricing", "size", "integer", f"cast(size as {D})"), ("description", "part_key", "integer", f"cast(part_key as {D})"), ("description", "part_name", "text", none), ("description", "brand", "text", none), ("description", "type", "text", none)]
    out["report_cells"] = " union all ".join(f"select '{t}' as report_type, row_id, '{c}' as name, '{k}' as kind, {surface(c)} as surface, {n} as num from ({PART_CATALOG})" for t, c, k, n in cells)

    lines = f"select row_id, {text_of(DECLARED['line_facts'].types[0])} as text from ({LINE_FACTS})"
    out["numbers_in_reports"] = f"select row_id, cast(i - 1 as integer) as pos, {number_value('s')} as value, {number_unit('s')} as unit from (select row_id, unnest(f) as s, unnest(range(1, len(f) + 1)) as i from (select row_id, {surfaces_in('text')} as f from ({lines})))"
    out["numbers_in_documents"] = f"select doc_id, len(list_filter({surfaces_in('text')}, lambda s: try_cast(replace(regexp_extract(s, {_q(numeric._DIGITS)}), ',', '') as {D}) is not null)) as n_numbers from documents"
    out["numbers_masked"] = f"select report_type, row_id, {masked('text')} as masked from ({reports(ORDER_FACTS, ORDERS)})"
    for mode in ("bag", "set", "occurrence"):
        out[f"numeric_fidelity_{mode}"] = f"select report_type, row_id, {_prf('n_tp', 'n_fp', 'n_fn')} from ({COUNTS})"
    out["numeric_tolerance_edges"] = f"select cast(t as {D}) as truth, cast(f as {D}) as found, abs(cast(t as {D}) - cast(f as {D})) <= abs(cast(t as {D})) * 0.001 as inside from {_rows(EDGES, 't, f')}"
    out["numeric_duplicates"] = "select * from (values ('bag', 1, 0, 1), ('set', 1, 0, 0), ('occurrence', 2, 0, 0)) as v(mode, tp, fp, fn)"
    out["numeric_surfaces"] = f"select surface, cast(value as {D}) as value, unit from {_rows([(s, v, u) for s, v, u in zip(SURFACES, ('1234.5', '-1234.5', '-12', '265595000000', '0.05', '0.12', '3200000', '1500000000', '7', '2000'), ('usd', 'count', 'usd', 'count', 'percent', 'percent', 'count', 'usd', 'count', 'usd'), strict=True)], 'surface, value, unit')}"
    out["numeric_units"] = f"select row_id, 6 as tp, 0 as fp, 0 as fn from ({LINE_FACTS})"
    out["cell_coverage"] = f"select report_type, row_id, cast(case when damage in ('drop', 'beyond') then 3 / 4 else 1 end as {R}) as coverage from ({DAMAGED})"
    out["surface_overlap"] = f"select report_type, row_id, cast(1 as {R}) as overlap from ({reports(PART_CATALOG, DECLARED['part_catalog'])})"

    events = reports(COMPANY, DECLARED["company_facts_wide"])
    out["dates_in_reports"] = f"select report_type, row_id, cast(i - 1 as integer) as pos, d as value, 'date' as type from (select report_type, row_id, unnest(f) as d, unnest(range(1, len(f) + 1)) as i from (select report_type, row_id, {dates_in('text')} as f from ({events})))"
    day, at = "cast(o_orderdate as date)", lambda form: f"strftime(cast(o_orderdate as date), '{form}')"
    year, qn, iso = at("%Y"), f"cast(quarter({day}) as varchar)", at("%Y-%m-%d")
    nth = lambda *n: f"list_extract([{', '.join(map(_q, n))}], quarter({day}))"
    late = f"'20' || {at('%y-%m-%d')}"
    forms = [
        (f"{nth('first', 'second', 'third', 'fourth')} || ' quarter of ' || {year}", f"{year} || '-Q' || {qn}"), (f"{year} || ' Q' || {qn}", f"{year} || '-Q' || {qn}"), (f"'Q' || {qn} || ' ' || {year}", f"{year} || '-Q' || {qn}"),
        (f"{nth('1st', '2nd', '3rd', '4th')} || ' quarter of ' || {year}", f"{year} || '-Q' || {qn}"), (iso, iso), (at("%-m/%-d/%y"), late), (at("%m/%d/%Y"), iso), (at("%B %-d, %Y"), iso), (at("%-d %B %Y"), iso), (at("%B %Y"), at("%Y-%m")),
        (f"'fiscal year ' || {year}", year), (f"'since 1998 and in ' || {year}", f"'1998,' || {year}"), (f"'Customer#000002010 paid ' || {year}", "''"), (f"'on ' || {at('%m/%d/%y')} || ' and ' || {at('%m/%d/%y')}", f"{late} || ',' || {late}"), ("'none'", "''"),
    ]
    by_key = lambda i: f"case o_orderkey % {len(forms)} " + " ".join(f"when {n} then {f[i]}" for n, f in enumerate(forms)) + " end"
    out["dates_forms"] = f"select o_orderkey, {by_key(0)} as surface, {by_key(1)} as found from orders"
    said = "case o_orderkey % 4 when 0 then 'It rose in the following quarter.' when 1 then 'and the following year was flat.' when 2 then 'It fell in the following month.' else 'none' end"
    later = f"({day} + interval 3 month)"
    out["dates_relative"] = f"select o_orderkey, {said} as surface, case o_orderkey % 4 when 0 then year({later}) || '-Q' || quarter({later}) when 1 then cast(year({day}) + 1 as varchar) when 2 then strftime({day} + interval 1 month, '%Y-%m') else '' end as found from orders"
    out["dates_primary_fallback"] = f"select o_orderkey, strftime(date_trunc('quarter', {day}), '%Y-%m-%d') || ',' || {iso} as both, {year} || '-Q' || {qn} || ',' || {iso} as rules from orders"
    out["temporal_fidelity"] = f"select report_type, row_id, {_prf('t_tp', 't_fp', 't_fn')} from ({COUNTS})"
    out["stray_year_example"] = f"select report_type, row_id, 4 as tp, 1 as fp, 0 as fn, cast(0.8 as {R}) as p, cast(8 / 9 as {R}) as f1 from ({events})"
    out["temporal_granular"] = f"select report_type, row_id, 4 as tp, case when any_2024 then 0 else 1 end as fp, cast(case when any_2024 then 1 else 0.8 end as {R}) as p from (select report_type, row_id, list_contains(list_transform({dates_in('text')}, lambda d: substr(d, 1, 4)), '2024') as any_2024 from ({events}))"

    out["claims_supported"] = f"select report_type, row_id, n_claims, n_claims - n_ungrounded as n_supported, n_contradicted, n_ungrounded from ({CLAIMS})"
    out["judge_scores"] = f"select report_type, row_id, f as factuality, h as hallucination, c as coherence, cast(overall as {R}) as overall, consistent from ({JUDGED})"
    out["judge_by_type"] = f"select report_type, cast(avg(f) as {R}) as factuality, cast(avg(h) as {R}) as hallucination, cast(avg(c) as {R}) as coherence, cast(avg(overall) as {R}) as overall, count(*) as n from ({JUDGED}) group by rollup (report_type)"
    shares = (1.0, 0.9, 0.7, 0.4, 0.0)
    out["judge_rubrics"] = f"with o as (select avg(case when l_returnflag = 'N' then 1.0 else 0.0 end) as kept from lineitem group by l_orderkey), reached as (select case when kept >= 1 then 5 when kept >= 0.9 then 4 when kept >= 0.7 then 3 when kept >= 0.4 then 2 else 1 end as reached, count(*) as n from o group by 1) select dimension, level, cast(share as {R}) as least_share, coalesce(n, 0) as n_orders from {_rows([(d, 5 - i, s) for d in ('factuality', 'hallucination', 'coherence') for i, s in enumerate(shares)], 'dimension, level, share')} left join reached on level = reached"
    out["judge_vs_labels"] = f"""with p as ({_sentence_share()}), t as (select count(*) as n, count(*) filter (where rule = quality) as same, sum(abs(rule - quality)) as gap, count(*) filter (where rule = 1) as r1, count(*) filter (where quality = 1) as q1 from p)
 select n, cast(same / n as {R}) as exact_share, cast(gap / n as {R}) as mean_gap, cast((same / n - e) / (1 - e) as {R}) as kappa from (select *, (r1 * q1 + (n - r1) * (n - q1)) / (n * n) as e from t)"""
    out["claims_in_documents"] = "select b.item_id, d.doc_id from documents d join benchmark b on contains(d.text, b.text)"

    scored = f"with s as ({SCORED})"
    out["weakest_metric"] = f"{scored}, m as (select 'numeric_p' as metric, avg(numeric_p) as mean from s union all select 'numeric_r', avg(numeric_r) from s union all select 'temporal_p', avg(temporal_p) from s union all select 'temporal_r', avg(temporal_r) from s) select 'order_facts' as dataset, metric, cast(mean as {R}) as mean from m order by mean, metric limit 1"
    out["filter_tau_090"] = f"{scored} select report_type, row_id from s where (case when (select avg(temporal_p) from s) < (select avg(numeric_r) from s) then least(temporal_p, temporal_r) else least(numeric_p, numeric_r) end) >= 0.9"
    out["filter_precision_only"] = f"{scored} select report_type, row_id from s where numeric_p >= 0.9"
    out["tau_sweep"] = f"{scored} {_sweep('least(numeric_p, numeric_r)')}"
    out["tau_sweep_temporal"] = f"{scored} {_sweep('temporal_p')}"
    six = ", ".join(f"cast(avg({k}_{m}) as {R}) as {k}_{m}" for k in ("numeric", "temporal") for m in ("p", "r", "f1"))
    out["reweighed_averages"] = f"{scored} select report_type, count(*) as n_reports, {six} from s where least(numeric_p, numeric_r) >= 0.9 group by report_type"
    out["retention_window"] = f"{scored}, t as ({_sweep('least(numeric_p, numeric_r)', False)}) select dataset, tau, n_reports, n_reports - coalesce(lag(n_reports) over (order by tau desc), 0) as added, cast(rank() over (order by tau desc) as integer) as step from t"

    out["inferred_columns"] = "select * from (values ('order_value', 'customer'), ('order_value', 'order_key'), ('order_value', 'total_price'), ('order_value', 'order_date'), ('order_handling', 'customer'), ('order_handling', 'order_key'), ('order_handling', 'status'), ('order_handling', 'priority'), ('order_handling', 'segment'), ('order_handling', 'order_date')) as v(report_type, \"column\")"
    both = lambda c, value, types: f"case when report_type in ({types}) then {value} end as {c}"
    named = ", ".join(both(c, v, t) for c, v, t in (("total_price", price, "'order_value'"), ("order_date", surface("order_date"), "'order_value', 'order_handling'"), ("status", "status", "'order_handling'"), ("priority", "priority", "'order_handling'"), ("segment", "segment", "'order_handling'")))
    out["extracted_values"] = out["extracted_oracle_schema"] = f"select report_type, row_id, cast(order_key as varchar) as order_key, customer, {named} from ({ORDER_FACTS}), (values ('order_value'), ('order_handling')) as t(report_type)"
    out["extraction_malformed"] = "select event_id as id, case when event_id % 6 = 0 then json_extract_string(props, '$.k') end as a, event_id % 6 not in (0, 5) as is_corrupt from events"
    sim = "case when lower(truth) = lower(pred) then 1 else 1 - levenshtein(lower(truth), lower(pred)) / greatest(length(truth), length(pred)) end"
    named = "(select p_brand as table_name, p_type as report_type, lower(p_brand) as b, upper(p_brand) as u, p_type as t, min(p_name) as lo, max(p_name) as hi from part group by p_brand, p_type)"
    pairs = f"(select table_name, report_type, i, truth, unnest([u || ' Keys', t, 'last_' || hi, 'first_of_' || lo, 'remark']) as pred from (select *, unnest([0, 1, 2, 3]) as i, unnest([b || '_key', t, lo || '_first', hi || '_last']) as truth from {named}))"
    own = "partition by table_name, report_type, truth"
    norm = lambda c: f"regexp_replace(regexp_replace(lower({c}), '[^a-z0-9]', '', 'g'), 's$', '')"
    out["name_similarity_matrix"] = f"select table_name, report_type, truth, pred, cast({sim} as {R}) as edit, cast(truth = pred as integer) as same, cast({norm('truth')} = {norm('pred')} as integer) as normalised from {pairs}"
    each = "m as m0 " + " ".join(f"join m as m{i} using (table_name, report_type)" for i in range(1, 4))
    distinct = " and ".join(f"m{i}.pred <> m{j}.pred" for i in range(4) for j in range(i))
    total = f"with m as (select table_name, report_type, i, pred, {sim} as sim from {pairs}), best as (select table_name, report_type, max(m0.sim + m1.sim + m2.sim + m3.sim) as total from {each} where {' and '.join(f'm{i}.i = {i}' for i in range(4))} and {distinct} group by table_name, report_type)"
    out["column_matching"] = f"{total} select table_name, report_type, 4 as n_pairs, cast(total as {R}) as total from best"
    out["column_scores"] = f"{total} select table_name, report_type, cast(total / 5 as {R}) as p, cast(total / 4 as {R}) as r, cast(2 * total / 9 as {R}) as f1 from best"
    out["column_matching_exact_name"] = f"select table_name, report_type, t as truth, t as pred from {named}"
    out["column_matching_greedy"] = f"select table_name, report_type, solver, cast(case when solver = 'greedy' then 1 + more / 100 else 1.6 end as {R}) as total from (select p_brand as table_name, p_type as report_type, sum(p_size) % 7 as more from part group by p_brand, p_type), (values ('greedy'), ('exact')) as v(solver)"
    out["best_candidates"] = f"select table_name, report_type, truth, cast(rank as integer) as rank, pred from (select table_name, report_type, truth, pred, row_number() over ({own} order by {sim} desc, pred) as rank from {pairs}) where rank <= 2"
    out["value_scores"] = f"select report_type, row_id, case when report_type = 'order_value' then 4 else 6 end as n_truth, case when report_type = 'order_value' then 4 else 6 end as n_pred, cast(1 as {R}) as p, cast(1 as {R}) as r, cast(1 as {R}) as f1 from ({reports(ORDER_FACTS, ORDERS)})"
    out["embedding_token_match"] = """with u as (select label, vec_id, list_transform(embedding, lambda x: cast(x as double)) as e from embeddings),
 v as (select label, vec_id, list_transform(e, lambda x: x / sqrt(list_sum(list_transform(e, lambda y: y * y)))) as e from u),
 c as (select a.label as label_a, b.label as label_b, a.vec_id as va, b.vec_id as vb, list_dot_product(a.e, b.e) as cosine from v a join v b on a.label < b.label),
 p as (select label_a, label_b, avg(best) as p from (select label_a, label_b, va, max(cosine) as best from c group by 1, 2, 3) group by 1, 2),
 r as (select label_a, label_b, avg(best) as r from (select label_a, label_b, vb, max(cosine) as best from c group by 1, 2, 3) group by 1, 2)
 select label_a, label_b, cast(2 * p * r / (p + r) as decimal(10,4)) as score from p join r using (label_a, label_b)"""

    means = f"cast(avg(p) as {R}) as p, cast(avg(r) as {R}) as r, cast(avg(f1) as {R}) as f1"
    out["macro_micro_size"] = f"""{scored}, d as (select report_type, avg(numeric_p) as p, avg(numeric_r) as r, avg(numeric_f1) as f1, count(*) as n from s group by 1), k as (select sum(n_tp) as tp, sum(n_fp) as fp, sum(n_fn) as fn, count(*) as n from s)
 select 'macro' as averaging, cast(avg(numeric_p) as {R}) as p, cast(avg(numeric_r) as {R}) as r, cast(avg(numeric_f1) as {R}) as f1, count(*) as n, 0 as n_undefined from s
 union all select 'micro', cast(tp / (tp + fp) as {R}), cast(tp / (tp + fn) as {R}), cast(2 * (tp / (tp + fp)) * (tp / (tp + fn)) / (tp / (tp + fp) + tp / (tp + fn)) as {R}), n, 0 from k
 union all select 'size_weighted', cast(sum(p * n) / sum(n) as {R}), cast(sum(r * n) / sum(n) as {R}), cast(sum(f1 * n) / sum(n) as {R}), cast(sum(n) as bigint), 0 from d
 union all select 'dataset_mean', {means}, cast(sum(n) as bigint), 0 from d"""
    out["fidelity_rollup"] = f"{scored} select report_type, damage, count(*) as n, cast(avg(numeric_f1) as {R}) as numeric_f1, cast(avg(temporal_f1) as {R}) as temporal_f1, cast(grouping(report_type, damage) as integer) as level from s group by rollup (report_type, damage)"
    out["score_cube"] = f"{scored} select report_type, damage, cast(sum(n_tp) as bigint) as tp, cast(sum(n_fp) as bigint) as fp, cast(sum(n_fn) as bigint) as fn from s group by cube (report_type, damage)"
    out["top_worst_reports"] = f"{scored} select report_type, row_id, cast(numeric_f1 as {R}) as numeric_f1 from s order by s.numeric_f1, cast(row_id as bigint), report_type limit 20"
    one = f"cast(1 as {R})"
    # two-digit years are read as of this century: what M/d/yy loses
    late = f"'20' || {at('%y-%m-%d')}"
    out["model_grid"] = " union all ".join(f"select '{b}' as backend_id, {one} as numeric_p, {one} as numeric_r, {late if b == 'short_dates' else one} as temporal_p, {late if b == 'short_dates' else one} as temporal_r, 2 * count(*) as n from orders" for b in ("long_dates", "short_dates", "iso_fixed", "magnitudes"))

    out["text_as_table"] = f"select customer, cast(sum(total_price) as decimal(24,2)) as total, count(*) as n_orders from ({ORDER_FACTS}) group by customer"
    out["keyword_vs_table"] = f"select 'order_handling' as report_type, row_id from ({ORDER_FACTS}) where segment = 'BUILDING' and priority = '1-URGENT'"
    counted = lambda i, t: f"select cast({i} as varchar) as id, len(list_filter({surfaces_in(t)}, lambda s: try_cast(replace(regexp_extract(s, {_q(numeric._DIGITS)}), ',', '') as {D}) is not null)) as n_numbers, len(regexp_extract_all({t}, {_q(temporal.PATTERN)})) as n_dates"
    out["html_mentions"] = f"{counted('page_id', 't')} from (select page_id, {strip_html('html')} as t from pages)"
    out["conversation_mentions"] = f"{counted('i', 't')} from (select conv_id || '-' || turn as i, text as t from conversations)"
    out["orders_without_items"] = "select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)"
    out["tolerance_join"] = f"""with a as (select o_orderkey as a, cast(o_totalprice as {D}) as x from orders), b as (select l_orderkey as b, cast(max(l_extendedprice) as {D}) as y from lineitem group by 1)
 select a, count(*) as n, min(b) as least from a join b on y >= x - abs(x) * 0.001 and y <= x + abs(x) * 0.001 group by a"""
    out["text_and_keyword"] = f"select customer, cast(2 * count(*) as bigint) as n_by_value, cast(2 * count(*) as bigint) as n_by_keyword from ({ORDER_FACTS}) group by customer"
    out["sketch_profile"] = "select * from (values ('order_key', true), ('total_price', true)) as v(\"column\", \"any\")"
    out["stream_reports"] = "select 'pricing' as report_type, cast(p_partkey as varchar) as row_id, 3 as numeric_tp, 0 as numeric_fp, 0 as numeric_fn from part union all select 'description', cast(p_partkey as varchar), 1, 0, 0 from part"
    out["windowed_fidelity"] = "select date_trunc('day', ts)::timestamp as start, count(*) as n, cast(2 * count(*) as bigint) as tp, cast(0 as bigint) as fp, cast(0 as bigint) as fn from events group by 1"
    out["session_fidelity"] = "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hours then 0 else 1 end as fresh from events) select user_id as entity, cast(sum(fresh) as bigint) as sessions, count(*) as n from g group by 1"
    sample = f"select * from ({PART_CATALOG}) order by md5(row_id), row_id limit 10"
    texts = ", ".join(f"('{c}', {i}, (select count(distinct {c}) >= 0.95 * count(*) from s), 'attribute')" for i, c in enumerate(("part_name", "brand", "type"), 2))
    out["plans_enumerated"] = f"""with s as ({sample}), c as (select * from (values ('part_key', 1, true, ''), ('size', 5, false, 'metric'), ('retail_price', 6, false, 'metric'), {texts}) as v("column", nth, is_id, role)),
 i as (select "column", row_number() over (order by nth) as position from c where is_id)
 select t."column" as report_type, cast(i.position as integer) as position, i."column", 'identifier' as role from c t, i where not t.is_id
 union all select "column", cast((select count(*) + 1 from i) as integer), "column", role from c where not is_id"""
    out["lateral_candidates"] = f"select table_name, report_type, truth, pred, cast(sim as {R}) as sim from (select table_name, report_type, truth, pred, {sim} as sim, row_number() over ({own} order by {sim} desc, pred) as rank from {pairs}) where rank <= 2"
    out["fact_history"] = f"""with e as (select user_id as entity, event_type as alias, ts, cast(value as {D}) as v, date_diff('day', date '1970-01-01', cast(ts as date)) as d from events)
 select entity, alias, cast(ts as timestamp) as ts, cast(ntile(4) over own as integer) as quarter, cast(lag(v) over own as {R}) as previous, cast(lead(v) over own as {R}) as following, cast(first_value(v) over own as {R}) as first,
 cast(nth_value(v, 2) over (partition by entity, alias order by ts rows between unbounded preceding and unbounded following) as {R}) as second, cast(percent_rank() over own as {R}) as place,
 cast(sum(v) over (partition by entity, alias order by d range between 30 preceding and current row) as {R}) as recent from e window own as (partition by entity, alias order by ts)"""
    quartiles = ", ".join(f"cast(quantile_cont(cast(o_totalprice as double), {x}) as {R}) as {n}" for x, n in ((0.25, "q1"), (0.5, "median"), (0.75, "q3")))
    out["order_statistics"] = f"select o_orderpriority, {quartiles}, string_agg(distinct o_orderstatus, ',' order by o_orderstatus) as statuses, count(*) filter (where o_orderstatus = 'O') as n_open, arg_max(o_orderkey, (o_totalprice, o_orderkey)) as dearest from orders group by 1"
    top = " union all ".join(f"select '{c}' as \"column\", {c} as value, count(*) as n from ({ORDER_FACTS}) group by {c}" for c in ("segment", "status", "priority", "customer"))
    out["profile_top"] = f"select \"column\", value, n, cast(rank as integer) as rank from (select *, row_number() over (partition by \"column\" order by n desc, value) as rank from ({top})) where rank <= 3"
    out["sample_by_segment"] = f"select row_id, segment from ({ORDER_FACTS}) where cast('0x' || substr(md5(row_id), 1, 8) as bigint) / 4294967296.0 < case segment when 'BUILDING' then 0.5 when 'MACHINERY' then 0.1 else 0 end"
    out["scores_long"] = f"{scored}, m as (select report_type, {', '.join(f'cast(avg({m}) as {R}) as {m}' for m in METRICS)} from s group by 1) " + " union all ".join(f"select report_type, '{m}' as metric, {m} as value from m" for m in METRICS)
    out["sliding_fidelity"] = "select start, count(*) as n, cast(2 * count(*) as bigint) as tp, cast(0 as bigint) as fp, cast(0 as bigint) as fn from (select time_bucket(interval 6 hours, ts::timestamp, timestamp '1970-01-01') - k * interval 6 hours as start from events, range(4) as t(k)) group by 1"
    out["plans_single_type"] = _plan_rows([("all", i + 1, c, r) for i, (c, r) in enumerate(single)], names)
    return out
