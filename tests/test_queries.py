"""Every query with SQL gives what the SQL gives, on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from rowblock import queries as core
from rowblock import relational_queries as around

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
PAIRS = sorted((core.ORACLES | around.ORACLES).items())


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def plain(v):
    return None if v is None or v != v else round(float(v), 9) + 0.0 if isinstance(v, float) else v


@pytest.mark.parametrize(("name", "sql"), PAIRS, ids=[n for n, _ in PAIRS])
def test_against_sql(spark, duck, sf, name, sql):
    df = (core.QUERIES | around.QUERIES)[name](spark, sf)
    names = sorted(df.columns)
    got = sorted(repr(tuple(plain(r[c]) for c in names)) for r in df.collect())
    cursor = duck.execute(sql)
    own = [d[0] for d in cursor.description]
    assert sorted(own) == names
    want = sorted(repr(tuple(plain(dict(zip(own, r, strict=True))[c]) for c in names)) for r in cursor.fetchall())
    assert got == want


def test_entry(spark):
    df = entry.entry(spark)
    assert df.columns[-4:] == ["q0", "q1", "q2", "q3"] and df.count() == 6000


def test_names_agree():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", sorted((core.QUERIES.keys() | around.QUERIES.keys()) - core.ORACLES.keys() - around.ORACLES.keys()))
def test_queries_without_sql_run(spark, sf, name):
    assert (core.QUERIES | around.QUERIES)[name](spark, sf).count() > 0
