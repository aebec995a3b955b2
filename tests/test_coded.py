import itertools

import numpy as np
import pytest

from curvetide.operators import coding as K
from curvetide.operators.sketch import BlockSketch
from curvetide.plans import coded as P
from curvetide.plans import optimise as O
from curvetide.plans.problems import Logistic, Ridge, Softmax, SquaredHinge
from curvetide.sources.design import DesignMatrix


def data(spark, n=70, d=7):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(n, d))
    y = np.where(x @ rng.normal(size=d) + 0.5 * rng.normal(size=n) > 0, 1.0, -1.0)
    return DesignMatrix(spark.createDataFrame([(i * 3, float(y[i]), [float(v) for v in x[i]]) for i in range(n)], "row_id long, y double, x array<double>"), d), x, y


def test_lost_blocks_are_signed_sums_of_others():
    g, size = 3, 4
    v = np.random.default_rng(0).normal(size=(1, 33))
    blocks = P.feature_blocks(v, g)[0]
    cells = [(r, c) for r in range(g + 1) for c in range(g + 1)]
    assert blocks.shape == (16, size)
    for n in (0, 1, 2, 3):
        for erased in itertools.combinations(cells, n):
            assert np.allclose(P.joined_blocks(blocks, set(erased), g, 33), v[0])
    many = {(0, 0), (0, 1), (1, 1), (1, 2), (2, 2), (3, 3)}
    assert np.allclose(P.joined_blocks(blocks, many, g, 33), v[0])
    with pytest.raises(ValueError):
        K.combinations({(0, 0), (0, 1), (1, 0), (1, 1)}, g)


def test_blocks_that_are_not_waited_for():
    t = np.arange(16.0)
    erased, when = K.arrived(t, 3)
    assert K.peel(erased, 3) is not None and when == 15.0 - len(erased) and len(erased) >= 3
    corner = np.full(16, 1.0)
    corner[[0, 1, 4, 5]] = [50, 60, 70, 80]  # a rectangle can't be peeled: its first one is awaited
    erased, when = K.arrived(corner, 3)
    assert when == 50.0 and erased == {(0, 1), (1, 0), (1, 1)}


@pytest.mark.parametrize("problem", [Logistic(0.01), Ridge(0.1), SquaredHinge(0.1)])
@pytest.mark.parametrize("grids", [(3, 2), (2, 1)])
def test_two_coded_rounds(spark, problem, grids):
    m, x, y = data(spark)
    w = np.linspace(-1, 1, 7)
    pair = P.CodedPair.encode(m, *grids)
    r = pair.evaluate(problem, w, it=2)
    assert all(r.erased) and r.n == len(y)
    assert np.allclose(r.gradient, problem.gradient(x, y, w) / len(y) + problem.reg_gradient(w))
    assert np.isclose(r.loss, problem.losses(x, y, [w])[0] / len(y) + problem.reg_loss(w))
    pair.release()


def test_written_pair_and_sketch(spark, tmp_path):
    m, x, y = data(spark)
    sk, problem, w = BlockSketch(3, 1, 8, 5), Logistic(0.01), np.full(7, 0.2)
    pair = P.CodedPair.encode(m, 3, 2, path=str(tmp_path))
    r = pair.evaluate(problem, w, sketch=sk)
    s = O.scan(m, problem, (), (), w, sk)
    a, b = (sorted(map(tuple, np.round(np.c_[v.block_of, v.rows], 9).tolist())) for v in (r, s))
    assert a == b


def test_placed_rows_fill_offsets_once(spark):
    df = spark.createDataFrame([(i,) for i in range(1000)], "row_id long")
    out, size = K.placed(df, 3, per=40)
    rows = out.collect()
    assert len({(r["r"], r["c"], r["offset"]) for r in rows}) == 1000 and max(r["offset"] for r in rows) < size
    ranks = K.ranked(df.repartition(5), "row_id").collect()
    assert all(r["rank"] == r["row_id"] for r in ranks)


def test_gradient_code_loses_the_slowest(spark):
    m, x, y = data(spark, 200)
    problem, w = Logistic(0.01), np.full(7, 0.1)
    want = problem.gradient(x, y, w) / len(y) + problem.reg_gradient(w)
    for workers, s in ((5, 1), (8, 3), (130, 3)):
        t = np.random.default_rng(workers).random(workers)
        assert np.allclose(P.coded_gradient(m, problem, w, workers, s, O._worker(workers), t), want)


def test_coded_fits_follow_plain_ones(spark):
    m, *_ = data(spark, 300)
    problem, sk = Logistic(0.05), BlockSketch(8, 2, 14, 3)
    pair = P.CodedPair.encode(m, 3, 2)
    for sketch in (None, sk):
        a, b = (O.newton(m, problem, sketch=sketch, iters=4, tol=0.0, coded=c) for c in (None, pair))
        assert np.allclose(a.w, b.w) and b.trace[-1]["sim_s"] > 0
    plain, by_code = (O.averaged_local_newton(m, problem, 6, policy, iters=3) for policy in (None, O.GradientCode(2)))
    assert np.allclose(plain.w, by_code.w)
    with pytest.raises(NotImplementedError):
        Softmax(3).at_margins(np.zeros(2), np.zeros(2))


def test_large_sketches_go_by_tiles(spark):
    m, *_ = data(spark, 200)
    sk = BlockSketch(6, 2, 10, 1)
    a, b = (O.sketched_newton(m, Logistic(0.05), sk, iters=3, tol=0.0, driver_bytes=n) for n in (1 << 30, 0))
    assert np.allclose(a.w, b.w)
    w = np.zeros(7)
    s = O.scan(m, Logistic(0.05), (), (), w, sk)
    for tile, group in ((3, 1), (7, 4), (100, 2)):
        assert np.allclose(O.tiled_hessian(m, Logistic(0.05), w, sk, [0, 2, 5], s.n or 200, tile, group), O.sketched_hessian(O.scan(m, Logistic(0.05), [w], (), w, sk), Logistic(0.05), w, [0, 2, 5]))
