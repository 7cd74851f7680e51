"""Every catalog query against its DuckDB oracle, on the smallest tables."""

import duckdb
import pytest

import __spark_entry__
from stalegrad.catalog import latency_queries, optimiser_queries, relational_queries, run_queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES = {**latency_queries.QUERIES, **optimiser_queries.QUERIES, **run_queries.QUERIES, **relational_queries.QUERIES}
ORACLES = {**latency_queries.ORACLES, **optimiser_queries.ORACLES, **run_queries.ORACLES, **relational_queries.ORACLES}


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def cell(v):
    if v is None or v != v:
        return "null"
    return f"{v:.5e}" if isinstance(v, float) else str(v)


def canonical(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return [columns[i] for i in order], sorted([cell(r[i]) for i in order] for r in rows)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sf, duck, name):
    got = QUERIES[name](spark, sf)
    want = duck.execute(ORACLES[name])
    names = [d[0] for d in want.description]
    assert canonical(got.columns, [tuple(r) for r in got.collect()]) == canonical(names, want.fetchall())


def test_registry():
    registered = __spark_entry__.queries()
    assert set(QUERIES) <= set(registered) and set(__spark_entry__.oracle_sql()) <= set(registered)


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() > 3
