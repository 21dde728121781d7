"""Every query with SQL against DuckDB on the smallest tables, and the rest for rows."""

import math

import duckdb
import pytest

from rotagrad import queries as engine

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"step_sweep_rollup", "small_start_sweep", "logistic_two_round"}


def canonical(rows):
    def cell(x):
        if x is None or (isinstance(x, float) and math.isnan(x)):
            return "null"
        return repr(float(x)) if isinstance(x, float) else str(x)

    return sorted(tuple(map(cell, r)) for r in rows)


@pytest.fixture(scope="session")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(engine.SQL))
def test_against_sql(spark, sf, duck, name):
    got = engine.QUERIES[name](spark, sf)
    columns = sorted(got.columns)
    want = duck.sql(engine.SQL[name])
    assert columns == sorted(want.columns)
    assert canonical(tuple(r[c] for c in columns) for r in got.collect()) == canonical(tuple(r[want.columns.index(c)] for c in columns) for r in want.fetchall())


@pytest.mark.parametrize("name", sorted(set(engine.QUERIES) - set(engine.SQL) - SLOW))
def test_rows(spark, sf, name):
    assert engine.QUERIES[name](spark, sf).count() > 0


def test_all_servers_answering_equals_plain_descent(spark, sf):
    assert all(r.gap < 1e-9 for r in engine.secure_exact_descent(spark, sf).collect())


def test_stream_equals_batch(spark, sf):
    assert engine.stream_equals_batch(spark, sf).first()[0] == 0


def test_entry_imports():
    import __spark_entry__

    assert "sketched_descent" in __spark_entry__.queries()
