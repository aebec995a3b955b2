"""Queries over whole tables, all workers and all features."""

import os

import numpy as np
import pytest

from curvetide import catalogue
from curvetide.plans import optimise as O

duckdb = pytest.importorskip("duckdb")
TABLES = "part lineitem embeddings".split()


@pytest.fixture(scope="module")
def larger(sf):
    return os.path.join(os.path.dirname(sf), "sf0.01")


def same_as_sql(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{p if os.path.isfile(p) else p + '/*.parquet'}'")
    df = catalogue.queries()[name](spark, sf)
    cur = con.execute(catalogue.oracle_sql()[name])
    got = df.select(*[d[0] for d in cur.description]).collect()
    text = lambda rows: sorted(tuple(f"{v:.6f}" if isinstance(v, float) else str(v) for v in r) for r in rows)
    assert text(tuple(r) for r in got) == text(cur.fetchall())
    return got, con


def test_cube_sums_the_table(spark, larger):
    rows, con = same_as_sql(spark, larger, "load_cube_whole")
    total, suppliers = con.execute("SELECT sum(l_quantity), count(DISTINCT l_suppkey) FROM lineitem").fetchone()
    assert suppliers > 20 and len({r["supp"] for r in rows}) == suppliers + 1
    assert [r["qty"] for r in rows if r["supp"] == r["brand"] == "all"] == [pytest.approx(total)]


@pytest.mark.parametrize("name, n", [("survivor_first_n_whole", 30000), ("survivor_lists_whole", 3000)])
def test_all_workers_of_all_trials(spark, sf, name, n):
    rows, _ = same_as_sql(spark, sf, name)
    assert len(rows) == n and {r["trial"] for r in rows} == set(range(10))


WIDE = [n for n in sorted(catalogue.oracle_sql()) if n.endswith("_whole") and n not in ("load_cube_whole", "arrival_table_whole", "survivor_first_n_whole", "survivor_lists_whole")]


@pytest.mark.parametrize("name", WIDE)
def test_all_features(spark, sf, name):
    rows, _ = same_as_sql(spark, sf, name)
    if "i" in rows[0].asDict():
        assert {r["i"] for r in rows} == set(range(64))
    if "k" in rows[0].asDict():
        assert {r["k"] for r in rows} == set(range(10))


@pytest.mark.parametrize("name", ["w05", "w06", "w08", "w16", "svm"])
def test_workloads_fit_all_features(spark, sf, name, monkeypatch):
    seen, scan = set(), O.scan
    monkeypatch.setattr(O, "scan", lambda data, problem, *a, **b: (seen.add(problem.width(data.d)), scan(data, problem, *a, **b))[1])
    catalogue.queries()[f"workload_{name}"](spark, sf)
    assert seen == {640 if name == "w05" else 64}


@pytest.mark.parametrize("name", ["sketch_gaussian", "sketch_hadamard_block"])
def test_other_embeddings_cover_all_features(spark, sf, name):
    rows = catalogue.queries()[name](spark, sf).collect()
    x = np.array([r[0] for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("embedding").collect()], float)
    h = np.zeros((64, 64))
    for r in rows:
        h[r["i"], r["j"]] = h[r["j"], r["i"]] = r["h"]
    assert len(rows) == 64 * 65 // 2 and np.linalg.norm(h - x.T @ x) < 0.6 * np.linalg.norm(x.T @ x)


@pytest.mark.parametrize("name", ["step_fixed_tuned", "race_any_n", "measure_embedding_eps", "measure_rate_bounds"])
def test_measures_take_all_features(spark, sf, name, monkeypatch):
    seen, scan = set(), O.scan
    monkeypatch.setattr(O, "scan", lambda data, *a, **b: (seen.add(data.d), scan(data, *a, **b))[1])
    assert catalogue.queries()[name](spark, sf).count() > 0 and seen == {64}
