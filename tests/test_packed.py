"""Rows packed in blocks give what plain rows give."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvetide.operators.sketch import BlockSketch
from curvetide.operators.vectors import packed
from curvetide.plans import optimise as O
from curvetide.plans import workloads
from curvetide.plans.arrivals import GradientCode, IgnoreStragglers, WaitAll
from curvetide.plans.problems import Logistic
from curvetide.sources import design
from curvetide.sources.design import DesignMatrix

P = Logistic(1e-2)


@pytest.fixture(scope="module")
def pair(spark, sf):
    """Plain rows, and packed ones that are laid out for 7 workers; some ids beyond 2**31."""
    d = design.embeddings(spark, sf)
    d = DesignMatrix(d.df.withColumn("row_id", F.col("row_id") * 1_000_003_000_001).cache(), 64)
    rows = O.place(7, 3)(d.df)
    return d, DesignMatrix(d.df, 64, 0, packed(rows, 64).persist(), 7, 3)


def test_workers_of_both_forms(pair):
    rows = pair[0].df.select("row_id", O._worker(7).alias("k")).toPandas()
    assert (O.worker_np(rows["row_id"].to_numpy(), 7) == rows["k"]).all()


def test_scan(pair):
    w, sk = np.linspace(-0.3, 0.3, 64), BlockSketch.of(640, 64, 0.2, seed=1)
    a, b = (O.scan(d, P, [w], [w], w, sk) for d in pair)
    assert a.n == b.n and np.allclose(a.losses, b.losses) and np.allclose(a.gradients, b.gradients)
    assert np.allclose(O.sketched_hessian(a, P, w, [0, 1, 2]), O.sketched_hessian(b, P, w, [0, 1, 2]))


@pytest.mark.parametrize("workers", [7, 4])
@pytest.mark.parametrize("policy, step", [(WaitAll(), None), (GradientCode(2), None), (IgnoreStragglers(0.8), None), (WaitAll(), O.ArmijoF())])
def test_averaging(pair, workers, policy, step):
    a, b = (O.averaged_local_newton(d, P, workers, policy, step, iters=2) for d in pair)
    assert np.allclose(a.w, b.w, rtol=1e-7, atol=1e-9) and a.trace[-1]["sim_s"] == b.trace[-1]["sim_s"]


def test_many_workers_need_a_layout(pair):
    with pytest.raises(ValueError):
        O.packed_direction(pair[1], P, np.zeros(64), np.zeros(64), 10**6)


def test_second_order_makes_no_job_for_each_worker(spark, sf, monkeypatch):
    """Gradients and directions of many workers leave their tasks complete: nothing is
    grouped by worker, and no plain rows are laid out for each fit."""
    def refuse(*a, **k):
        raise AssertionError("plain rows")

    monkeypatch.setattr(O, "by_worker", refuse)
    monkeypatch.setattr(O, "coded_gradient", refuse)
    make = lambda place: design.synthetic(spark, sf, 6, place=place)
    rows = workloads._second_order("t", make, 4, Logistic(1e-4), 10, 1, (60, 3600, 600), 1.67, iters=1)
    assert len({r[1] for r in rows}) == 10 and all(r[9] is not None and np.isfinite(r[9]) for r in rows if r[2] == 0)


def test_synthetic_rows_as_columns_draw_them(spark, sf):
    from curvetide.functions import columns as X

    d, w = design.synthetic(spark, sf, 5), design.planted_weights(5)
    x = design.uniform_features(F.col("row_id"), 5)
    y = design.planted_label(X.dot(x, X.weights(w[:5])) + w[5], F.col("row_id"))
    same = d.df.select((F.col("x") == x).alias("x"), (F.col("y") == y).alias("y")).groupBy("x", "y").count().collect()
    assert [(r["x"], r["y"]) for r in same] == [(True, True)]


def test_fits_share_passes(spark, sf, monkeypatch):
    """Ten fits of one iteration need no more passes than the longest of them, and held-out
    rows one."""
    seen, passed = [], O.passed
    monkeypatch.setattr(O, "passed", lambda data, requests: (seen.append(len(requests)), passed(data, requests))[1])
    make = lambda place: design.synthetic(spark, sf, 6, place=place)
    workloads._second_order("t", make, 4, Logistic(1e-4), 10, 1, (60, 3600, 600), 1.67, iters=1)
    assert seen[0] == 10 and seen[-1] == 10 and len(seen) == 5


def test_shared_passes_change_no_fit(pair):
    fits = [lambda d: O.sketched_newton(d, P, BlockSketch.of(640, 64, 0.2, seed=1), iters=3), *[lambda d, k=k, p=p: O.averaged_local_newton(d, P, k, p, iters=2) for k in (7, 4) for p in (GradientCode(2), IgnoreStragglers(0.8))]]
    for fit, got in zip(fits, O.side_by_side(pair[1], fits)):
        alone = fit(pair[1])
        assert np.allclose(got.w, alone.w, rtol=1e-12) and len(got.trace) == len(alone.trace) and got.scheme == alone.scheme


def test_a_failed_pass_fails_each_fit_that_waits(pair):
    def bad(d):
        return O.scan(d, P, [np.zeros(3)])

    with pytest.raises(Exception, match="matmul|mismatch"):
        O.side_by_side(pair[1], [bad, lambda d: O.exact_newton(d, P, iters=1)])


def test_whole_numbers_are_packed_as_bytes(spark):
    from curvetide.operators.vectors import rows_of

    small, other = [[0.0, 1.0, -128.0], [127.0, 5.0, 0.0]], [[0.5, -0.0, 1e300], [float("nan"), 128.0, float("inf")]]
    for x, size in ((small, 1), (other, 8), ([[0.0, -0.0, 1.0]], 8), ([[128.0, 0.0, 0.0]], 8)):
        blocks = packed(spark.createDataFrame([(i, 1.0, v) for i, v in enumerate(x)], "row_id long, y double, x array<double>").coalesce(1), 3)
        assert sum(len(r["xs"]) for r in blocks.collect()) == size * 3 * len(x)
        got = [r for _, _, v in rows_of(blocks.toArrow().to_batches(), 3) for r in v]
        assert (np.array(got).view(np.int64) == np.array(x).view(np.int64)).all()


def test_sides_of_a_split_are_packed_by_one_evaluation(pair):
    both = workloads._laid(pair[0], 4, 7)
    for side, rows in zip(both, pair[0].split(4)):
        w = np.linspace(-0.3, 0.3, 64)
        a, b = O.scan(side, P, [w], [w]), O.scan(rows, P, [w], [w])
        assert a.n == b.n and np.allclose(a.losses, b.losses) and np.allclose(a.gradients, b.gradients)
    both[2].unpersist()


def test_slices():
    assert [workloads.slices(b << 20, 6) for b in (1, 7, 200, 300, 2000)] == [1, 2, 12, 12, 66]
