import datetime as dt

import duckdb

from tabletext.llm import url_filter

D = dt.date


def entries(spark, rows):
    return spark.createDataFrame(rows, "list string, pattern string, day date, action string")


def test_validity_and_levels(spark):
    listed = entries(spark, [
        ("a", "bad.com", D(2024, 1, 10), "add"), ("a", "bad.com", D(2024, 2, 1), "remove"), ("a", "bad.com", D(2024, 3, 1), "add"),
        ("b", "x.bad.com", D(2024, 1, 1), "add"), ("b", "ok.org/forum", D(2024, 1, 1), "add"), ("c", "day.com", D(2024, 1, 5), "add"), ("c", "day.com", D(2024, 1, 5), "remove"),
        ("d", None, D(2024, 1, 1), "add"), ("d", "ok.org", None, "add"), ("a", "bad.com", D(2024, 1, 10), "add"),
    ])
    seen = [
        (1, "http://bad.com/", D(2024, 1, 9), ""), (2, "http://bad.com/", D(2024, 1, 10), "a:bad.com"), (3, "https://u:p@X.BAD.com:80/q?x#y", D(2024, 1, 31), "a:bad.com,b:x.bad.com"),
        (4, "http://bad.com", D(2024, 2, 1), ""), (5, "http://www.bad.com./", D(2024, 12, 1), "a:bad.com"), (6, "http://notbad.com/", D(2024, 1, 20), ""),
        (7, "http://ok.org/Forum/1", D(2024, 1, 20), "b:ok.org/forum"), (8, "http://ok.org/forums/1", D(2024, 1, 20), ""), (9, "http://day.com/", D(2024, 1, 5), ""),
        (10, None, D(2024, 1, 20), ""), (11, "no url", D(2024, 1, 20), ""), (12, "http://bad.com/", None, ""), (2, "http://bad.com/", D(2024, 1, 10), "a:bad.com"),
    ]
    captures = spark.createDataFrame([x[:3] for x in seen], "page_id long, url string, fetched date")
    got = sorted((r["page_id"], r["matches"], r["blocked"]) for r in url_filter.filter_captures(captures, listed).collect())
    assert got == sorted((x[0], x[3], bool(x[3])) for x in seen)
    assert {r["page_id"] for r in url_filter.keep_allowed(captures, listed).collect()} == {x[0] for x in seen if not x[3]}
    assert url_filter.filter_captures(captures.limit(0), listed.limit(0)).count() == 0


def test_against_sql(spark, sf):
    got = [tuple(r) for r in url_filter.op3(spark.read.parquet(f"{sf}/pages.parquet")).collect()]
    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{sf}/pages.parquet'")
    want = con.execute(url_filter.SQL).fetchall()
    assert sorted(got) == sorted(want) and any(r[3] for r in got) and not all(r[3] for r in got)


def test_captures_of_one_page_are_judged_each(spark):
    """A page fetched before and after it was listed loses the later capture alone; ids may be null, columns clash."""
    listed = entries(spark, [("a", "bad.com", D(2024, 2, 1), "add")])
    rows = [(1, "http://bad.com/", D(2024, 1, 1), "x"), (1, "http://bad.com/", D(2024, 3, 1), "y"), (None, "http://bad.com/", D(2024, 3, 1), "z"), (None, "http://ok.com/", D(2024, 3, 1), "w"), (2, "http://ok.com/", None, "v")]
    captures = spark.createDataFrame(rows, "page_id long, url string, fetched date, matches string").selectExpr("*", "matches as host", "1 as row")
    kept = url_filter.keep_allowed(captures, listed)
    assert kept.columns == captures.columns and sorted(r["matches"] for r in kept.collect()) == ["v", "w", "x"]
    assert url_filter.filter_captures(captures, listed).where("blocked").count() == 2
