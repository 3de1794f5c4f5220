"""The short ways for usual texts, surfaces and cues give what the long ways give, on odd ones too."""

from pyspark.sql import functions as F

from tabletext.functions import fidelity, numeric, temporal
from tabletext.operators import extraction

TEXTS = [
    "order key 31521 and part key 9346. Its tax is 2.00%.", "Customer#000000012 paid $1,234.50", "5-LOW ABCdef9 7", "5-LOW_a9 8", "a_-_-5 b__6 c#-7x_ 12", "from 10.0.0.12 and 1.2.3 to 4.5",
    "+(030) 555-1234 then 12 555 1234 9999", "quantity-4 -4 (4) x", "1-a 2-b 3-URGENT NOW4 5", "_9 #9 -9 9_ 9#", "", "no digits at all", "1995-03-04a5 March 3, 1995b6", "99 100 and 1000 2000",
]
SURFACES = ["17.00", "-5", "$75,462.67", "-$3.1", "$-3", "4.00%", "4 %", "5 percent", "(12.5)", "($1,000)", "3 million", "1e5", "1,2,3.", "1,", ".5", "+5", "", "x", "9" * 20, "-" + "9" * 18, "0.0000005", "-0.0000015%", "5\n", "5%\n", "12-", "%-5"]
DATES = ["May 5, 2020", "March 31, 1995", "May 5, 2020\n", "5 May 2020", "2020-05-05", "5/5/20", "Mayo 5, 2020", "May 555, 2020", "fiscal year 2024", "2nd quarter of 2020", "Q1 2020", "May 2020", ""]


def both(spark, values, one, other):
    df = spark.createDataFrame([(v,) for v in values], "s string").repartition(2)
    rows = df.select("s", one(F.col("s")).alias("a"), other(F.col("s")).alias("b")).collect()
    assert len(rows) == len(values)
    for r in rows:
        assert r["a"] == r["b"], r


def test_masking_is_that_of_the_identifiers(spark):
    both(spark, TEXTS, numeric.mask_non_numeric, lambda s: F.regexp_replace(temporal.mask_dates(s), numeric.IDENTIFIERS, " "))
    both(spark, TEXTS, lambda s: F.regexp_replace(s, numeric.MASKED, " "), lambda s: F.regexp_replace(s, numeric.IDENTIFIERS, " "))
    both(spark, TEXTS + SURFACES, lambda s: F.regexp_extract_all(s, F.lit(numeric.SCAN), F.lit(0)), lambda s: F.regexp_extract_all(s, F.lit(numeric.PATTERN), F.lit(0)))


def test_usual_surfaces_are_read_as_all_are(spark):
    both(spark, [*SURFACES, None], numeric.normalise_number, numeric._normalised)
    both(spark, [*DATES, None], temporal.normalise_date, temporal._normalised)


def test_a_null_pairs_with_nothing(spark):
    cases = [("array(1, null, 2)", "array(2, 1)", 2), ("array(null)", "array(null)", 0), ("array(1000, 5)", "array(5, 1001)", 2), ("array(1, 1, 3)", "array(1, 3, 3)", 2), ("array()", "array()", 0)]
    for truth, found, tp in cases:
        of = lambda x: F.expr(f"cast({x} as array<decimal(24,6)>)")
        assert spark.range(1).select(fidelity.paired(of(truth), of(found))).first()[0] == tp, (truth, found)
    days = lambda x: F.expr(f"cast({x} as array<string>)")
    assert spark.range(1).select(fidelity.match_dates(days("array('a', null)"), days("array('a', null)"))["tp"]).first()[0] == 1


def test_one_pattern_reads_the_values_of_all_columns(spark):
    texts = [
        "This report covers order key 7 and customer Customer#1. Its total price is $3.00. Its order date came to May 5, 2020.", "Its total price of old. Its total price is $4.00. Its total price is $5.00.",
        "Its total price is ??? and total price 6. x", "a covers total price 9. Its total price is 8.", "Its total priced is 8.", "", "Its a+b is 3. Its a.b is 4.",
    ]
    for name in ("total_price", "order_key", "customer", "order_date", "a+b", "a.b", "absent"):
        both(spark, [*texts, None], lambda s, n=name: extraction.extract_value(s, F.lit(n)), lambda s, n=name: extraction._searched(s, F.lit(n)))
