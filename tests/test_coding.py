import itertools

import numpy as np
import pytest

from curvetide.operators import coding as K


def blocks(spark, n=23, d=3):
    x = np.random.default_rng(0).normal(size=(n, d))
    return x, spark.createDataFrame([(i, 100 + i, [float(v) for v in x[i]]) for i in range(n)], "rank long, row_id long, x array<double>")


def test_three_erasures_always_peel_and_rectangles_never():
    cells = [(r, c) for r in range(4) for c in range(4)]
    assert all(K.peel(set(e), 3) is not None for n in (0, 1, 2, 3) for e in itertools.combinations(cells, n))
    stuck = [e for e in itertools.combinations(cells, 4) if K.peel(set(e), 3) is None]
    assert len(stuck) == 36 and all(len({r for r, _ in e}) == len({c for _, c in e}) == 2 for e in stuck)


@pytest.mark.parametrize("erased", [set(), {(0, 0)}, {(3, 3), (3, 0), (1, 3)}, {(0, 0), (0, 1), (1, 1), (2, 3)}])
def test_decoded_product(spark, erased):
    x, df = blocks(spark)
    w = [0.5, -1.0, 2.0]
    code = K.ProductCode.encode(df, len(x), 3)
    got = {r["row_id"]: r["y"] for r in code.decode(code.products(w), erased).collect()}
    assert np.allclose([got[100 + i] for i in range(len(x))], x @ w)


def test_undecodable_is_an_error(spark):
    _, df = blocks(spark)
    code = K.ProductCode.encode(df, 23, 3)
    with pytest.raises(ValueError):
        code.decode(code.products([1.0, 1.0, 1.0]), {(0, 0), (0, 1), (1, 0), (1, 1)})


def test_wait_set():
    order = [(r, c) for r in range(3) for c in range(3)]
    n = K.wait_set(order, 2)
    assert K.peel(set(order[n:]), 2) is not None and K.peel(set(order[n - 1 :]), 2) is None
    assert K.decode_rate(6, 0.02, 300) > 0.97 > K.decode_rate(9, 0.2, 300)


@pytest.mark.parametrize("w,s", [(4, 1), (6, 2), (5, 0), (8, 3)])
def test_any_survivors_give_the_sum(w, s):
    g = np.random.default_rng(1).normal(size=(w, 5))
    code = K.cyclic_code(w, s)
    assert ((code != 0).sum(axis=1) == s + 1).all()
    for live in itertools.combinations(range(w), w - s):
        assert np.allclose(K.decode_vector(code, list(live)) @ (code[list(live)] @ g), g.sum(axis=0), atol=1e-6)


def test_fractional_code_and_refusals():
    code = K.fractional_code(6, 1)
    for live in itertools.combinations(range(6), 5):
        K.decode_vector(code, list(live))
    for call in (lambda: K.fractional_code(5, 1), lambda: K.cyclic_code(3, 3), lambda: K.decode_vector(K.cyclic_code(4, 1), [0, 1])):
        with pytest.raises(ValueError):
            call()


def test_any_k_of_n():
    g = K.mds_code(4, 3)
    assert np.allclose(g[:4], np.eye(4))
    for live in itertools.combinations(range(7), 4):
        assert np.linalg.cond(g[list(live)]) < 1e6


def test_single_parity(spark):
    """Two halves and their sum: any two of three workers."""
    x = np.arange(12.0).reshape(6, 2)
    w = np.array([1.0, -2.0])
    a, b = x[:3] @ w, x[3:] @ w
    assert np.allclose((x[:3] + x[3:]) @ w - b, a)
