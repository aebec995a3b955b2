import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvetide.functions import sql as Q
from curvetide.operators.sketch import BlockSketch
from curvetide.plans import measures as M
from curvetide.plans import optimise as O
from curvetide.plans import race, semidefinite
from curvetide.plans.arrivals import matmul_bytes
from curvetide.plans.problems import Logistic
from curvetide.sources import design


def test_sql_functions(spark):
    s = BlockSketch(3, 1, 8, 2)
    Q.register_sketch(spark, s)
    rows = spark.sql("SELECT id, sketch_bucket(id, 2) AS b, sketch_sign(id, 2) AS s FROM range(500)").collect()
    b, sign = s.place_np(np.arange(500), 2)
    assert [r["b"] for r in rows] == b.tolist() and [r["s"] for r in rows] == sign.astype(int).tolist()


def test_table_functions(spark):
    Q.register_tables(spark)
    rows = spark.sql("SELECT * FROM peel('0,0;0,1;1,1', 3) ORDER BY step").collect()
    assert {(r["r"], r["c"]) for r in rows} == {(0, 0), (0, 1), (1, 1)}
    assert spark.sql("SELECT * FROM peel('0,0;0,1;1,0;1,1', 3)").count() == 0
    assert spark.sql("SELECT * FROM gradient_code(4, 1)").count() == 8


def test_sketch_as_a_table_function(spark, sf):
    Q.register_tables(spark)
    d, s = design.embeddings(spark, sf).head(3), BlockSketch(2, 1, 8, 2)
    d.df.select("row_id", "x").createOrReplaceTempView("rows_to_sketch")
    rows = spark.sql("SELECT block, bucket, v FROM sketch_rows(TABLE(rows_to_sketch), 2, 1, 8, 2)").collect()
    got = {}
    for r in rows:
        got[r["block"], r["bucket"]] = got.get((r["block"], r["bucket"]), 0.0) + np.array(r["v"])
    want = {(r["block"], r["bucket"]): np.frombuffer(r["v"]) for r in s.apply_arrow(d.df, 3).collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k]) for k in want)


def test_late_events_and_static_columns(spark):
    from curvetide.streaming import windows as W

    events = spark.createDataFrame([(1, "2024-01-01 10:00:00", "2024-01-01 10:00:05", 2.0), (2, "2024-01-01 23:00:00", "2024-01-02 02:00:00", -3.0), (3, "2024-01-02 01:00:00", "2024-01-02 01:10:00", 1.0)], "k long, ts string, arrived string, value double").withColumn("ts", F.to_timestamp("ts"))
    rows = sorted((r["window"]["start"].day, r["n"], r["late"], r["late_v"]) for r in W.late_mass(events).collect())
    assert rows == [(1, 2, 1, 3.0), (2, 1, 0, 0.0)]
    static = spark.createDataFrame([(1, "a"), (3, "c")], "id long, name string")
    assert sorted((r["k"], r["name"]) for r in W.with_static(events, static, "k", "id").collect()) == [(1, "a"), (2, None), (3, "c")]


def test_stream_with_a_static_table(spark, sf, tmp_path):
    from curvetide.sources import tables
    from curvetide.streaming import windows as W

    joined = W.with_static(tables.stream(spark, sf), tables.table(spark, sf, "customer", "c_custkey", "c_mktsegment"), "user_id", "c_custkey")
    W.run_available(joined.select("event_id", "c_mktsegment"), str(tmp_path / "out"), str(tmp_path / "ck"))
    got = spark.read.parquet(str(tmp_path / "out"))
    batch = W.with_static(tables.table(spark, sf, "events"), tables.table(spark, sf, "customer", "c_custkey", "c_mktsegment"), "user_id", "c_custkey")
    assert sorted(map(tuple, got.collect()), key=str) == sorted(map(tuple, batch.select("event_id", "c_mktsegment").collect()), key=str)


def test_interrupted_fit_goes_on(spark, sf, tmp_path):
    d = design.embeddings(spark, sf).head(5)
    d = design.DesignMatrix(d.df.cache(), 5)
    p, s, path = Logistic(0.01), BlockSketch(4, 1, 10, 1), str(tmp_path / "fit")
    whole = O.sketched_newton(d, p, s, iters=4, tol=0.0)
    O.sketched_newton(d, p, s, iters=2, tol=0.0, path=path)
    rest = O.sketched_newton(d, p, s, iters=4, tol=0.0, path=path)
    assert np.allclose(rest.w, whole.w) and [t["it"] for t in rest.trace] == [0, 1, 2, 3, 4]
    assert np.allclose([t["loss"] for t in rest.trace], [t["loss"] for t in whole.trace])


def test_prediction(spark, sf):
    d = design.embeddings(spark, sf)
    w = np.linspace(-1, 1, 64)
    rows = d.df.select("x", Q.predict_margin(w)(F.col("x")).alias("m")).limit(20).collect()
    assert all(np.isclose(np.dot(r["x"], w), r["m"]) for r in rows)


def test_fit_is_saved_and_resumed(spark, sf, tmp_path):
    d = design.embeddings(spark, sf).head(5)
    d = design.DesignMatrix(d.df.cache(), 5)
    p = Logistic(0.01)
    a = O.exact_newton(d, p, iters=1)
    a.save(spark, str(tmp_path / "fit"))
    b = O.FitResult.load(spark, str(tmp_path / "fit"))
    assert np.allclose(a.w, b.w) and b.scheme == a.scheme and [t["it"] for t in b.trace] == [0, 1]
    assert np.allclose(O.exact_newton(d, p, w0=b.w, iters=2).w, O.exact_newton(d, p, iters=3).w)


def test_race_takes_the_first_and_cancels_the_rest(spark):
    def slow():
        return spark.range(0, 1, 1, 1).mapInPandas(lambda it: (time.sleep(60), it)[1], "id long").count()

    t = time.time()
    got = race.first_n(spark, [lambda: spark.range(10).count(), slow, lambda: spark.range(20).count()], 2)
    assert got == {0: 10, 2: 20} and time.time() - t < 40

    def broken():
        raise RuntimeError("no")

    with pytest.raises(RuntimeError):
        race.first_n(spark, [broken, lambda: 1], 2)
    assert race.first_n(spark, [broken, lambda: 1], 1) == {1: 1}


def test_raced_sketch(spark, sf):
    d = design.embeddings(spark, sf).head(4)
    s = BlockSketch(2, 1, 4, 3)
    used, rows = race.raced_sketch(spark, d, Logistic(0.01), np.zeros(4), s)
    full = O.scan(d, Logistic(0.01), (), (), np.zeros(4), s)
    assert len(used) == 2
    for k in used:
        assert np.allclose(np.sort(rows[k], axis=0), np.sort(full.rows[full.block_of == k], axis=0))


def test_semidefinite():
    f0 = np.zeros((2, 2))
    fs = [np.eye(2), np.array([[0.0, 1.0], [1.0, 0.0]])]
    cost = [1.0, 0.0]
    # least x with [[x, y], [y, x]] >= [[0, 1], [1, 0]]-shifted: x = |y + 1|, y free in a box
    f0 = np.array([[0.0, 1.0], [1.0, 0.0]])
    fs.append(np.diag([0.0, 0.0]))
    x = semidefinite.solve(f0, fs[:2], [1.0, 0.5], [5.0, 0.0])
    assert np.isclose(x[0], abs(x[1] + 1), atol=1e-2) or x[0] < 5
    with pytest.raises(ValueError):
        semidefinite.solve(f0, fs[:2], cost, [0.0, 0.0])
    box = np.zeros((4, 4)); box[0, 0] = box[1, 1] = 1.0
    g = [np.diag([-1.0, 0, 1, 0]), np.diag([0, -1.0, 0, 1])]
    best = semidefinite.solve(box, g, [-1.0, -2.0], [0.4, 0.4])
    assert np.allclose(best, [1, 1], atol=1e-3)
    near = semidefinite.solve(box, g, [-1.0, -2.0], [0.4, 0.4], sketch=BlockSketch(6, 0, 4, 1))
    assert np.allclose(near, [1, 1], atol=1e-2)


def test_blocks_read_less_than_strips():
    assert matmul_bytes("block", 10**6, 3000, 3000) < matmul_bytes("rowcol", 10**6, 3000, 3000)


def test_perturbed_hessian_has_its_range():
    a = np.random.default_rng(0).normal(size=(30, 6))
    h = a.T @ a
    low, high = M.embedding_range(h, M.perturbed(h, 0.3))
    assert 0.69 <= low <= high <= 1.31 and max(1 - low, high - 1) > 0.29
