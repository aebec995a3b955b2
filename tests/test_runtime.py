import numpy as np
import pytest
from pyspark.sql import functions as F

from curvetide.plans import arrivals as A
from curvetide.plans import measures as M
from curvetide.sources import design, tables
from curvetide.streaming import windows


def test_arrivals_have_the_published_shape(spark):
    model = A.ArrivalModel()
    t = np.concatenate([model.draw(3600, k) for k in range(10)])
    assert abs(np.median(t) - 135) < 1 and 0.015 < (t > 145).mean() < 0.025 and t.max() <= 180
    rows = {(r["trial"], r["worker"]): r["t"] for r in model.table(spark, 50, 2).collect()}
    assert np.allclose([rows[1, w] for w in range(50)], model.draw(50, 1))


def test_policies_in_order():
    model = A.ArrivalModel()
    t, t2 = model.draw(3600), model.draw(3600, attempt=1)
    wait = A.WaitAll().finish(t, t2)
    assert A.AnyN(10, 2).finish(t, t2) < wait and A.CodedGrid().finish(t, t2) < wait and A.IgnoreStragglers(0.9).finish(t, t2) < wait
    assert A.GradientCode(1).finish(t, t2) > wait and A.Replicate().finish(t, t2) <= wait
    s = A.Speculative(0.9).finish(t, t2)
    assert A.CodedGrid().finish(t, t2) < s  # relaunching costs a whole second job
    assert A.AnyN(10, 2).finish(t[:5], t2[:5]) <= t[:5].max()


def test_costs():
    assert A.workers("matvec", 49) == 49 + 14 + 1 and A.workers("sketched", d=10, b=5, n=4, spare=1) == 20
    assert A.choose_hessian(10**9, 3000, 10, 2, 3000, 100) == "sketched" and A.choose_hessian(10**6, 10, 10, 2, 10, 1000) == "exact"
    with pytest.raises(ValueError):
        A.comm_bytes("none", 1, 1)


def test_trace_measures(spark):
    rows = [("w", s, i, 0.5 * r**i, 0.0, 1.0, float(i * dt), 0.0, "") for s, r, dt in (("a", 0.1, 5), ("b", 0.5, 1)) for i in range(8)]
    tr = tables.trace_frame(spark, rows)
    times = {r["scheme"]: r["t"] for r in M.time_to_target(tr, 0.01).collect()}
    assert times == {"a": 10.0, "b": 6.0}
    assert {r["scheme"]: round(r["saved"], 3) for r in M.speed_up(M.time_to_target(tr, 0.01), "a").collect()} == {"a": 0.0, "b": 0.4}
    assert {r["scheme"]: r["iters"] for r in M.iters_to_target(tr, 0.01).collect()} == {"a": 2, "b": 6}
    assert all(abs(r["ratio"] - {"a": 0.1, "b": 0.5}[r["scheme"]]) < 1e-9 for r in M.contraction(tr, 0.0).collect())
    got = {(r["scheme"], r["t"]): r["loss"] for r in M.aligned(tr, spark.createDataFrame([(0.0,), (7.0,)], "t double")).collect()}
    assert np.isclose(got["a", 7.0], 0.05) and np.isclose(got["b", 7.0], 0.5 * 0.5**7)


def test_sources(spark, tmp_path, sf):
    w = np.arange(5.0)
    tables.save_vector(spark, w, str(tmp_path / "w"))
    assert np.allclose(tables.load_vector(spark, str(tmp_path / "w")), w)
    (tmp_path / "s.txt").write_text("+1 1:0.5 7:2\n-1 3:1e-2\n")
    r = tables.read_sparse_text(spark, str(tmp_path / "s.txt")).collect()
    assert [(x["y"], x["idx"], x["val"]) for x in r] == [(1.0, [1, 7], [0.5, 2.0]), (-1.0, [3], [0.01])]
    (tmp_path / "a.csv").write_text("1,x\nz,y\n")
    with pytest.raises(Exception):
        tables.read_examples(spark, str(tmp_path / "a.csv"), "csv", "a int, b string").collect()
    trace = tables.trace_frame(spark, [("w", "s", 0, 1.0, 0.0, 1.0, 0.0, 0.0, "")])
    tables.save_trace(trace, str(tmp_path / "t"))
    tables.save_trace(trace, str(tmp_path / "t"))
    assert spark.read.parquet(str(tmp_path / "t")).count() == 2


def test_design(spark, sf):
    for make, d in ((design.embeddings, 64), (design.embeddings_multi, 64), (lambda a, b: design.synthetic(a, b, 5), 5), (design.numeric, 6), (lambda a, b: design.doc_terms(a, b, 20), 20)):
        m = make(spark, sf)
        m.validate()
        assert m.d == d
        train, test = m.split(4)
        assert train.df.count() + test.df.count() == m.df.count() and train.df.join(test.df, "row_id").count() == 0
    bad = spark.createDataFrame([(1, 1.0, [1.0, None]), (2, 1.0, [float("nan"), 0.0])], "row_id long, y double, x array<double>")
    with pytest.raises(ValueError):
        design.DesignMatrix(bad, 2).validate()
    design.DesignMatrix(design.clean(bad, "zero"), 2).validate()
    assert design.clean(bad, "drop").count() == 0
    with pytest.raises(Exception):
        design.clean(bad).collect()


def test_plans_push_down_and_prune(spark, sf):
    text = tables.settings(tables.table(spark, sf, "lineitem").where("l_quantity > 45").select("l_orderkey", "l_extendedprice"))
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in text
    assert "l_comment" not in text and "l_tax" not in text


def test_stream_equals_batch(spark, sf, tmp_path):
    out = windows.tumbling(windows.timed(tables.stream(spark, sf)))
    windows.run_available(out, str(tmp_path / "o"), str(tmp_path / "c"))
    batch = windows.tumbling(windows.timed(tables.table(spark, sf, "events")))
    want = {r["window"]["start"]: (r["n"], round(r["v"], 6)) for r in batch.collect()}
    got = {r["window"]["start"]: (r["n"], round(r["v"], 6)) for r in spark.read.parquet(str(tmp_path / "o")).collect()}
    assert got and got.items() <= want.items() and len(got) >= len(want) - 2  # the last windows stay open


def test_stream_sketch_and_warm_start(spark, sf, tmp_path):
    e = windows.timed(tables.table(spark, sf, "events"))
    day = windows.sketch_by_window(e)
    total = day.groupBy("block", "bucket").agg(F.sum("v").alias("v"))
    late = day.where(F.col("window.start") >= "2024-01-01")
    rest = windows.without(total, late)
    assert rest.count() <= total.count()
    state = {}
    windows.warm_newton(windows.timed(tables.stream(spark, sf)), lambda b, w: (w or 0) + b.count(), state, str(tmp_path / "k"))
    assert state["w"] == e.count()
    out = windows.dedup(windows.timed(tables.stream(spark, sf)))
    windows.run_available(out.select("event_id"), str(tmp_path / "d"), str(tmp_path / "dc"))
    assert spark.read.parquet(str(tmp_path / "d")).count() == e.count()
