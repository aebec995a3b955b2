"""Held-out curves and the measured rates."""

import numpy as np

from curvetide import catalogue
from curvetide.plans import optimise as O
from curvetide.plans.problems import Logistic
from curvetide.sources import design
from curvetide.sources.tables import trace_frame


def test_held_out_curve(spark, sf):
    train, test = design.embeddings(spark, sf).head(4).split(4)
    p = Logistic(0.01)
    fit = O.exact_newton(train, p, iters=2).tested(test, p)
    rows = test.df.collect()
    x, y = np.array([r["x"] for r in rows]), np.array([r["y"] for r in rows])
    for t in fit.trace:
        m = x @ t["w"]
        assert np.isclose(t["test_error"], np.mean(np.where(m > 0, 1.0, -1.0) != y))
        assert np.isclose(t["test_loss"], np.mean(np.logaddexp(0, -y * m)) + 0.005 * t["w"] @ t["w"])
    kept = trace_frame(spark, fit.rows("x")).where("test_loss IS NOT NULL AND test_error IS NOT NULL").count()
    assert kept == len(fit.trace)


def test_points_that_diverged_have_no_test_loss(spark, sf):
    train, test = design.embeddings(spark, sf).head(2).split(4)
    fit = O.FitResult(np.zeros(2), [{"w": np.array([np.nan, 0.0])}, {"w": np.zeros(2)}], "s")
    fit.tested(test, Logistic(0.01))
    assert "test_loss" not in fit.trace[0] and np.isclose(fit.trace[1]["test_loss"], np.log(2))


def test_rate_bounds_hold(spark, sf):
    rows = catalogue.queries()["measure_rate_bounds"](spark, sf).collect()
    assert {r["kind"] for r in rows} == {"strong", "weak"} and all(r["holds"] for r in rows)


def test_larger_sketches_are_closer(spark, sf):
    rows = catalogue.queries()["measure_embedding_eps"](spark, sf).orderBy("multiple").collect()
    eps = [r["eps_median"] for r in rows]
    assert eps == sorted(eps, reverse=True) and rows[-1]["failures"] == 0
