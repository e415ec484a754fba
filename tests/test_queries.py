"""Every registered query of the engine beside its SQL, on the smallest tables."""

import glob
import os

import duckdb
import pytest

from backtrail import deep_queries, queries, surface_queries

SMALL = "/root/testdata/sf0.001"
ALL = queries.QUERIES | deep_queries.QUERIES | surface_queries.QUERIES
SQL = queries.SQL | deep_queries.SQL | surface_queries.SQL


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    con.sql("SET TimeZone = 'UTC'")
    for path in glob.glob(f"{SMALL}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


def normal(value):
    return round(value, 6) if isinstance(value, float) else value


@pytest.mark.parametrize("name", list(ALL))
def test_query(spark, db, name):
    df = ALL[name](spark, SMALL)
    got = sorted(repr(tuple(normal(r[c]) for c in sorted(df.columns))) for r in df.collect())
    assert name in SQL
    found = db.sql(SQL[name])
    order = [found.columns.index(c) for c in sorted(found.columns)]
    assert sorted(df.columns) == sorted(found.columns)
    assert got == sorted(repr(tuple(normal(r[i]) for i in order)) for r in found.fetchall())


def test_every_query_has_sql():
    assert set(ALL) == set(SQL)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(ALL) <= set(__spark_entry__.queries())
