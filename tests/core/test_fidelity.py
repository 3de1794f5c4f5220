from decimal import Decimal
from itertools import permutations
from random import Random

import pytest
from pyspark.sql import functions as F

from tabletext.functions import fidelity, numeric, similarity, temporal

T = "array<decimal(24,6)>"


def one(spark, column):
    return spark.range(1).select(column.alias("x")).first()["x"]


def test_bag_of_dates_counts_repetitions(spark):
    """Five mentions, four true days, all found, one stray year."""
    text = "Cash was booked for 12/31/24, filed on 2/6/25. Income was booked for 12/31/24, filed on 2/6/25. So closed the fiscal year 2024."
    truth = F.array(*map(F.lit, ["2024-12-31", "2025-02-06", "2024-12-31", "2025-02-06"]))
    found = temporal.values(temporal.parse_dates(F.lit(text)))
    m = one(spark, fidelity.match_dates(truth, found))
    assert (m.tp, m.fp, m.fn, m.p, m.r) == (4, 1, 0, 0.8, 1.0) and round(m.f1, 4) == 0.8889
    granular = one(spark, fidelity.match_dates(truth, found, "granular"))
    assert (granular.tp, granular.fp, granular.p) == (4, 0, 1.0)
    as_set = one(spark, fidelity.match_dates(truth, found, "set"))
    assert (as_set.tp, as_set.fp) == (2, 1)


def best_pairing(truth, found):
    if len(truth) > len(found):
        found, truth, swap = truth, found, True
    else:
        swap = False
    near = lambda t, f: abs(t - f) <= abs(t) * Decimal("0.001")
    return max((sum(near(*(reversed((a, b)) if swap else (a, b))) for a, b in zip(truth, p, strict=False)) for p in permutations(found, len(truth))), default=0)


def test_pairing_is_the_largest(spark):
    r = Random(4)
    rows = []
    for i in range(60):
        base = [Decimal(r.choice([100, 100.05, 100.1, 100.15, 100.2, 0, -5, -5.004, 3])).quantize(Decimal("0.000001")) for _ in range(9)]
        rows.append((i, base[: r.randint(0, 5)], base[5 : 5 + r.randint(0, 4)]))
    df = spark.createDataFrame(rows, f"i int, t {T}, f {T}")
    got = {x["i"]: x["tp"] for x in df.select("i", fidelity.paired(F.col("t"), F.col("f")).alias("tp")).collect()}
    assert got == {i: best_pairing(t, f) for i, t, f in rows}


def test_counts_add_up_and_f1_is_at_most_the_mean(spark):
    r = Random(5)
    rows = [(i, [Decimal(r.randint(1, 6)) for _ in range(r.randint(0, 6))], [Decimal(r.randint(1, 6)) for _ in range(r.randint(0, 6))]) for i in range(80)]
    df = spark.createDataFrame(rows, f"i int, t {T}, f {T}")
    for mode in ("bag", "set", "occurrence"):
        for x in df.select("t", "f", fidelity.match_numbers(F.col("t"), F.col("f"), mode).alias("m")).collect():
            m, n_t, n_f = x["m"], len(set(x["t"]) if mode == "set" else x["t"]), len(set(x["f"]) if mode == "set" else x["f"])
            assert m.tp + m.fn == n_t and (mode == "occurrence" or m.tp + m.fp == n_f)
            if m.f1 is not None and m.p is not None and m.r is not None:
                assert m.f1 <= (m.p + m.r) / 2 + 1e-9


def test_identifiers_and_dates_are_no_numbers(spark):
    text = "Customer#000000012 of Brand#17 paid $1,234.50 on May 3, 2021, priority 1-URGENT, from 10.0.0.12, 5.00% off, 2.5 million units"
    found = one(spark, numeric.parse_numbers(F.lit(text)))
    assert [(float(m.value), m.unit) for m in found] == [(1234.5, "usd"), (0.05, "percent"), (2500000.0, "count")]


def test_malformed_text_is_harmless(spark):
    for s in ("", "$", "1,,2", "e5", "99999999999999999999999999999999", "((5)", None):
        assert one(spark, numeric.parse_numbers(F.lit(s).cast("string"))) is not None
        assert one(spark, temporal.parse_dates(F.lit(s).cast("string"))) == []


@pytest.mark.parametrize(("a", "b", "want"), [("abc", "abc", 1.0), ("Abc", "aBC", 1.0), ("", "", 1.0), ("abcd", "abce", 0.75), ("été", "ete", 1 / 3), ("a", "", 0.0)])
def test_edit_similarity(spark, a, b, want):
    for x, y in ((a, b), (b, a)):
        assert one(spark, similarity.sim_edit(F.lit(x), F.lit(y))) == pytest.approx(want)


def test_embedding_similarity():
    same, near, far = (similarity.sim_embedding_names("total_price", x) for x in ("Total Price", "total_prices", "segment"))
    assert same == pytest.approx(1) and same > near > far


def test_a_number_covers_one_cell(spark):
    """A key within the tolerance of the price says nothing of a price that the text leaves out or alters."""
    cells = F.expr(f"array(named_struct('name', 'order_key', 'kind', 'integer', 'surface', '143835', 'num', cast(143835 as decimal(24,6)), 'day', cast(null as date)), named_struct('name', 'total_price', 'kind', 'money', 'surface', '$143,760.40', 'num', cast(143760.40 as decimal(24,6)), 'day', cast(null as date)))")
    for more, want in (("", 0.5), (" Its total price is $145,199.00.", 0.5), (" Its total price is $143,832.28.", 1.0), (" Its total price is $143,760.40.", 1.0)):
        text = F.lit("This report covers order key 143835." + more)
        assert one(spark, fidelity.cell_coverage(cells, text, numeric.values(numeric.parse_numbers(text)), temporal.values(temporal.parse_dates(text)))) == want


def test_scan_finds_what_the_pattern_finds(spark):
    r = Random(3)
    parts = ["May", "May 3, 2023", "3 May 2023", "12/31/24", "2024-01-02", "first quarter of 2024", "2nd quarter of 2024", "2024 Q3", "Q3 2024", "fiscal year 2024", "in 1999", "of 2001", "x", "_", "-", "\u00e9", "\u0301", "second", "since 20"]
    rows = [("".join(r.choice(parts) + r.choice(["", " ", ", "]) for _ in range(9)),) for _ in range(3000)]
    found = lambda p: F.regexp_extract_all("text", F.lit(p), F.lit(0))
    df = spark.createDataFrame(rows, "text string").select(found(temporal.PATTERN).alias("a"), found(temporal.SCAN).alias("b"))
    assert df.where("a <> b").count() == 0 and df.where("size(a) > 1").count() > 1000
