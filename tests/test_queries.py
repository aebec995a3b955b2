"""Queries against their DuckDB twins (a part of them here; the driver runs all)."""

import os

import pytest

import __spark_entry__ as E
from curvetide import catalogue

duckdb = pytest.importorskip("duckdb")
NAMES = sorted(catalogue.oracle_sql())
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        p = f"{sf}/{t}.parquet"
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p if os.path.isfile(p) else p + '/*.parquet'}'")
    return c


def canonical(rows):
    return sorted(tuple(f"{v:.6f}" if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("name", NAMES[::4])
def test_query_equals_sql(spark, sf, con, name):
    df = catalogue.queries()[name](spark, sf)
    cur = con.execute(catalogue.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    want = cur.fetchall()
    assert sorted(names) == sorted(df.columns)
    assert canonical(tuple(r) for r in df.select(*names).collect()) == canonical(want)


def test_entry(spark):
    assert E.entry(spark).count() > 3
    assert set(E.oracle_sql()) <= set(E.queries())
