"""Every query with SQL gives what the SQL gives, on the smallest tables."""

import duckdb
import pytest

from tabletext import queries as q

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: the plan of ten sampled rows depends on whether a customer comes twice among them
BY_DATA = {"plan_orders"}


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


def normal(rows, names):
    order = sorted(range(len(names)), key=names.__getitem__)
    return sorted(tuple(str(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", [n for n in q.oracle_sql() if n not in BY_DATA])
def test_query(spark, sf, con, name):
    df = q.queries()[name](spark, sf)
    want = con.execute(q.oracle_sql()[name])
    names = [d[0] for d in want.description]
    assert sorted(df.columns) == sorted(names)
    assert normal([tuple(r) for r in df.collect()], df.columns) == normal(want.fetchall(), names)


def test_every_key_has_a_query():
    assert set(q.oracle_sql()) <= set(q.queries())


@pytest.mark.parametrize("name", ["best_candidates", "column_matching", "column_matching_exact_name", "column_matching_greedy", "column_scores", "lateral_candidates", "name_similarity_matrix"])
def test_names_come_from_a_table(spark, sf, name):
    assert any("part.parquet" in f for f in q.queries()[name](spark, sf).inputFiles())


@pytest.mark.parametrize(("name", "table"), [("dates_forms", "orders"), ("dates_relative", "orders"), ("dates_primary_fallback", "orders"), ("extraction_malformed", "events"), ("judge_rubrics", "lineitem")])
def test_forms_come_from_a_table(spark, sf, name, table):
    assert any(f"{table}.parquet" in f for f in q.queries()[name](spark, sf).inputFiles())
