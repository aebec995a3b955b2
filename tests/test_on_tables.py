"""Queries of arrivals, costs and codes read a given table, and equal their SQL there."""

import os

import numpy as np
import pytest

from curvetide import catalogue
from curvetide.plans import arrivals as A

duckdb = pytest.importorskip("duckdb")
NAMES = ["arrival_ranks", "arrival_summary", "arrival_table", "arrival_table_whole", "blocks_surviving_anti", "cost_comm", "cost_equalised", "cost_matmul_partition", "cost_rollup", "cost_workers", "gradient_code_placement", "math_logistic_stable"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_table_and_equals_sql(spark, sf, name):
    df = catalogue.queries()[name](spark, sf)
    assert any(t in f for f in df.inputFiles() for t in ("orders", "lineitem", "customer"))
    con = duckdb.connect()
    for t in ("orders", "lineitem", "customer"):
        p = f"{sf}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p if os.path.isfile(p) else p + '/*.parquet'}'")
    want = con.execute(f"SELECT {', '.join(df.columns)} FROM ({catalogue.oracle_sql()[name]})").fetchall()
    assert want and sorted(map(str, want)) == sorted(str(tuple(r)) for r in df.collect())


def test_hash_of_large_keys_in_sql():
    from curvetide.functions.hashing import coefficients, hash_np, hash_sql_long

    ids = np.array([0, 5, 2**31 - 1, 2**31, 2**40 + 12345, 2**61 - 7])
    got = [duckdb.execute(f"SELECT {hash_sql_long(f'{i}::BIGINT', coefficients(11, 1))}").fetchall()[0][0] for i in ids]
    assert got == hash_np(ids, coefficients(11, 1)).tolist()


def test_costs_as_the_scalar_functions_count_them(spark, sf):
    q = catalogue.queries()
    comm = {r["supplier"]: r for r in q["cost_comm"](spark, sf).collect()}
    product = {r["supplier"]: r for r in q["cost_matmul_partition"](spark, sf).collect()}
    for r in q["cost_workers"](spark, sf).collect():
        d, c, k = r["d"], comm[r["supplier"]], -(-r["d"] // 50)
        n, e = 10 * k, 2 * k
        assert (r["matvec"], r["sketched"], r["exact"], r["reduction"]) == (A.workers("matvec", n), A.workers("sketched", d=d, b=50, n=n, spare=e), A.workers("exact", d=d, b=50, n=n), A.workers("reduce", d=d, b=50))
        want = [A.comm_bytes("gradient", c["n"], d, tasks=64), A.comm_bytes("exact", c["n"], d, tasks=64), A.comm_bytes("sketched", c["n"], d, n, 50, e, 64), A.comm_bytes("encode", c["n"], d)]
        assert [c[x] for x in ("gradient", "exact", "sketched", "encode")] == want
        p = product[r["supplier"]]
        assert (p["block"], p["rowcol"]) == (A.matmul_bytes("block", p["n"], d, 50), A.matmul_bytes("rowcol", p["n"], d, 50))


def test_order_statistics(spark):
    rng = np.random.default_rng(0)
    t = {0: np.round(rng.uniform(0, 0.02, 501), 4), 1: np.array([3.5]), 2: np.full(40, 1.25)}
    df = spark.createDataFrame([(k, float(x)) for k, v in t.items() for x in v], "trial int, t double")
    got = {r["trial"]: (r["a"], r["b"]) for r in A.order_statistics(df, {"a": lambda n: n, "b": lambda n: (n + 1) / 2}).collect()}
    assert got == {k: (np.sort(v)[-1], np.sort(v)[(len(v) + 1) // 2 - 1]) for k, v in t.items()}
    assert A.order_statistics(df.where("trial > 5"), {"a": lambda n: n}).count() == 0
