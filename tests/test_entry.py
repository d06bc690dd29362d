"""The registry, and queries against their SQL on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"wave_profile_docs_u"}


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    shown = lambda v: round(float(v), 6) if isinstance(v, float) or type(v).__name__ == "Decimal" else v
    return sorted(columns), sorted((tuple(shown(r[i]) for i in order) for r in data), key=repr)


def test_entry(spark):
    assert entry.entry(spark).columns == ["query_id", "vec_id", "sim", "pos"]


def test_every_sql_has_its_query():
    assert entry.oracle_sql().keys() <= entry.queries().keys()
    assert len(entry.queries()) > 100


@pytest.mark.parametrize("name", [n for n in entry.oracle_sql() if not n.startswith("op1_") and n not in SLOW])
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.sql(entry.oracle_sql()[name])
    got = entry.queries()[name](spark, SF)
    assert rows(got.columns, [tuple(r) for r in got.collect()]) == rows(want.columns, want.fetchall())
