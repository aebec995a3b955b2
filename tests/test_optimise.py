import numpy as np
import pytest

from curvetide.operators.sketch import BlockSketch
from curvetide.plans import measures as M
from curvetide.plans import optimise as O
from curvetide.plans import solve as V
from curvetide.plans.arrivals import FUNCTIONS, SERVERS, GradientCode, IgnoreStragglers
from curvetide.plans.problems import LassoDual, LinearProgram, Logistic, Ridge, Softmax, SquaredHinge
from curvetide.sources import design


@pytest.fixture(scope="module")
def emb(spark, sf):
    d = design.embeddings(spark, sf).head(10)
    return design.DesignMatrix(d.df.cache(), 10)


@pytest.fixture(scope="module")
def xy(emb):
    r = sorted(emb.df.collect(), key=lambda x: x["row_id"])
    return np.array([x["x"] for x in r]), np.array([x["y"] for x in r])


RNG = np.random.default_rng(0)
X, Y = RNG.uniform(-1, 1, (40, 5)), np.where(RNG.random(40) < 0.5, 1.0, -1.0)
CASES = [(Logistic(0.1), Y, RNG.normal(size=5)), (Softmax(3), RNG.integers(0, 3, 40).astype(float), RNG.normal(size=15)), (Ridge(0.2), RNG.normal(size=40), RNG.normal(size=5)), (LinearProgram(RNG.normal(size=5), 2.0), np.full(40, 6.0), 0.1 * RNG.normal(size=5)), (LassoDual(RNG.normal(size=5), 3.0, 2.0), Y, 0.1 * RNG.normal(size=5))]


@pytest.mark.parametrize("problem,y,w", CASES)
def test_derivatives(problem, y, w):
    n = len(X) if problem.mean else 1
    f = lambda v: problem.losses(X, y, [v])[0] / n + problem.reg_loss(v)
    g = lambda v: problem.gradient(X, y, v) / n + problem.reg_gradient(v)
    a = problem.root(X, y, w)
    h = a.T @ a / n + problem.reg_hessian(w)
    for i in range(len(w)):
        e = np.eye(len(w))[i] * 1e-5
        assert np.isclose((f(w + e) - f(w - e)) / 2e-5, g(w)[i], atol=1e-5)
        assert np.allclose((g(w + e) - g(w - e)) / 2e-5, h[:, i], atol=1e-4)


def test_softmax_null_space():
    a = Softmax(3).root(X, np.zeros(40), RNG.normal(size=15))
    assert np.allclose(a @ np.tile(RNG.normal(size=5), 3), 0, atol=1e-12)


def test_large_margins_do_not_overflow():
    with np.errstate(over="raise"):
        p = Logistic(0.0)
        x, y = np.array([[1000.0], [-1000.0]]), np.array([1.0, 1.0])
        assert np.allclose(p.losses(x, y, [np.ones(1)]), 1000) and np.isfinite(p.gradient(x, y, np.ones(1))).all()


def test_scan_matches_numpy(emb, xy):
    x, y = xy
    p, w = Logistic(0.01), np.linspace(-1, 1, 10)
    s = O.scan(emb, p, [w, 0 * w], [w], w, fan=3)
    assert s.n == len(y) and np.isclose(s.losses[0], p.losses(x, y, [w])[0] / len(y) + p.reg_loss(w))
    assert np.allclose(s.gradients[0], p.gradient(x, y, w) / len(y) + 0.01 * w)
    assert np.isclose(s.errors, p.errors(x, y, w) / len(y))
    a = p.root(x, y, w)
    assert np.allclose(s.gram, a.T @ a / len(y) + 0.01 * np.eye(10))


def test_exact_newton_is_quadratic_and_sketched_follows(emb):
    p = Logistic(1e-2)
    exact = O.exact_newton(emb, p, iters=5)
    assert exact.trace[-1]["grad_norm"] < 1e-9
    gaps = []
    for m in (50, 200):
        fit = O.sketched_newton(emb, p, BlockSketch.of(m * 10, 20, 0.2, seed=3), iters=5)
        gaps.append(fit.loss - exact.loss)
        losses = [t["loss"] for t in fit.trace]
        assert all(b <= a + 1e-12 for a, b in zip(losses, losses[1:]))
    assert -1e-12 <= gaps[1] <= gaps[0] + 1e-9 < 1e-5


def test_same_seed_same_fit(emb):
    run = lambda df: O.sketched_newton(design.DesignMatrix(df, 10), Logistic(0.01), BlockSketch.of(100, 20, 0.2), iters=2).w
    assert np.allclose(run(emb.df.repartition(1)), run(emb.df.repartition(9)))


def test_guard_and_line_search(emb):
    fit = O.newton(emb, Logistic(1e-4), np.full(10, 40.0), step=O.ArmijoF(), iters=6)
    assert fit.loss < 0.72 and any(t["step"] < 1 for t in fit.trace)
    tiny = O.sketched_newton(emb, Logistic(1e-4), BlockSketch.of(10, 10, 0.0, seed=2), iters=7)
    assert np.isfinite(tiny.loss)


def test_weakly_convex(spark, sf):
    d = design.embeddings_multi(spark, sf).head(4)
    d = design.DesignMatrix(d.df.cache(), 4)
    p = Softmax(10)
    fit = O.exact_newton(d, p, iters=5)
    assert fit.trace[-1]["grad_norm"] < 1e-6
    sk = O.sketched_newton(d, p, BlockSketch.of(800, 40, 0.2), iters=4)
    assert sk.trace[-1]["grad_norm"] < sk.trace[0]["grad_norm"]
    with pytest.raises(ValueError):
        O.averaged_local_newton(d, p)


def test_first_order_and_local(emb):
    p = Logistic(1e-2)
    best = O.exact_newton(emb, p, iters=5).loss
    gd, nag, sgd = O.gradient_descent(emb, p, iters=4), O.nesterov(emb, p, iters=4), O.sgd(emb, p, iters=3)
    assert all(f.trace[0]["loss"] > f.loss >= best - 1e-12 for f in (gd, nag))
    assert np.isfinite(sgd.loss)
    for policy in (None, GradientCode(1), IgnoreStragglers(0.75)):
        fit = O.averaged_local_newton(emb, p, 4, policy, iters=3)
        assert fit.loss - best < (5e-3 if isinstance(policy, IgnoreStragglers) else 1e-3)
    assert O.averaged_local_newton(emb, p, 4, iters=2, profile=SERVERS).trace[-1]["sim_s"] < O.averaged_local_newton(emb, p, 4, iters=2, profile=FUNCTIONS).trace[-1]["sim_s"]
    assert O.tune_fixed_step(emb, p, (1.0, 0.1), iters=2) == 1.0


def test_svm(emb):
    fit = O.exact_newton(emb, SquaredHinge(1e-2), step=O.ArmijoF(), iters=5)
    assert fit.trace[-1]["grad_norm"] < 1e-8


def test_linear_program(spark):
    rows = [(0, 1.0, [1.0, 0.0]), (1, 1.0, [0.0, 1.0]), (2, 1.5, [1.0, 1.0]), (3, 0.0, [-1.0, 0.0]), (4, 0.0, [0.0, -1.0])]
    d = design.DesignMatrix(spark.createDataFrame(rows, "row_id long, y double, x array<double>").cache(), 2)
    fit = O.barrier(d, lambda t: LinearProgram([-2.0, -1.0], t), [0.3, 0.3], tau=1.0, growth=20.0, stages=4, inner=8)
    assert np.allclose(fit.w, [1.0, 0.5], atol=1e-3)
    with pytest.raises(ValueError):
        O.barrier(d, lambda t: LinearProgram([-2.0, -1.0], t), [2.0, 2.0])


def test_lasso_recovery(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(6, 12))
    y = x[:, 0] * 1.5 - x[:, 3]
    bound = 0.3 * np.abs(x.T @ y).max()
    rows = [(j, 0.0, [float(v) for v in x[:, j]]) for j in range(12)]
    d = design.DesignMatrix(spark.createDataFrame(rows, "row_id long, y double, x array<double>").cache(), 6)
    fit = O.barrier(d, lambda t: LassoDual(y, bound, t), np.zeros(6), tau=10.0, growth=10.0, stages=5, inner=8)
    w = LassoDual(y, bound, 10.0 * 10**4).primal(x.T @ fit.w)
    ref = np.zeros(12)
    for _ in range(3000):
        for j in range(12):
            r = x[:, j] @ (y - x @ ref + x[:, j] * ref[j])
            ref[j] = np.sign(r) * max(abs(r) - bound, 0) / (x[:, j] @ x[:, j])
    assert np.allclose(w, ref, atol=2e-2)


def test_solvers(spark):
    rng = np.random.default_rng(4)
    a = rng.normal(size=(8, 8))
    h, g = a.T @ a + np.eye(8), rng.normal(size=8)
    x = np.linalg.solve(h, g)
    assert np.allclose(V.solve_spd(h, g), x) and np.allclose(V.cg(lambda p: h @ p, g), x, atol=1e-6) and np.allclose(V.minres(lambda p: h @ p, g), x, atol=1e-6)
    low = a[:, :5] @ a[:, :5].T
    want = np.linalg.pinv(low) @ g
    assert np.allclose(V.pinv_solve(low, g), want, atol=1e-6)
    assert np.linalg.norm(low @ V.minres(lambda p: low @ p, g) - g) <= np.linalg.norm(low @ want - g) + 1e-6
    df = spark.createDataFrame([(i, j, float(h[i, j])) for i in range(8) for j in range(i, 8)], "i int, j int, h double")
    assert np.allclose(V.cg_distributed(df, g), x, atol=1e-5)


def test_quality_improves_with_size(emb, xy):
    x, y = xy
    p, w = Logistic(1e-2), np.zeros(10)
    h = O.scan(emb, p, hessian_at=w).gram
    mean = []
    for m in (5, 50):
        eps = []
        for seed in range(6):
            sk = BlockSketch.of(m * 10, 10, 0.0, seed=seed)
            s = O.scan(emb, p, (), (), w, sk)
            eps.append(M.embedding_eps(h, O.sketched_hessian(s, p, w, list(range(sk.blocks)))))
        mean.append(np.mean(eps))
    assert mean[1] < mean[0]
    c = M.constants(h, O.scan(emb, p, (), [w]).gradients[0])
    assert 0 < c["k"] <= c["M"] and 0 < c["nu"] <= 1 + 1e-9
    assert 0 < M.global_rate(1.0, 0.1, c["k"], c["M"], 0.1) < 1 and M.least_step(0.1, 0.1, c["k"], c["M"]) > 0
    assert 0 < M.weak_rate(0.5, 0.1, c["nu"], 0.1, c["eta"], c["M"]) < 1 and M.weak_step(0.1, 1.0, 0.0, 1.0, 1.0, 1.0, 0.0) > 0
    assert M.local_bound(0.1, 1, 1, 0.01, 1) > 0 and M.local_bound_applies(0.01, 1, 1) and M.failure_rate([0.1, 0.6], 0.5) == 0.5
