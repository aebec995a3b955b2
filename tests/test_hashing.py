import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from curvetide.functions import columns as X
from curvetide.functions.hashing import P, coefficients, hash_col, hash_np, uniform_np


def test_sql_and_numpy_agree(spark):
    ids = [0, 1, P - 1, P, P + 1, 2 * P - 1, 2 * P, 3 * P + 7, 123456789012345, (1 << 61) - 1]
    coef = coefficients(3, 4)
    df = spark.createDataFrame([(i,) for i in ids], "id long").select(hash_col(F.col("id"), coef).alias("h"))
    assert [r["h"] for r in df.collect()] == hash_np(np.array(ids), coef).tolist()


@settings(max_examples=50, deadline=None)
@given(st.integers(0, (1 << 61) - 1), st.integers(0, 50), st.integers(0, 200))
def test_hash_is_the_polynomial(i, seed, block):
    c = coefficients(seed, block)
    lo, hi = i % P, i // P
    h = ((c[0] * lo + c[1]) * lo + c[2]) * lo + c[3]
    g = ((c[4] * hi + c[5]) * hi + c[6]) * hi
    assert hash_np(np.array([i]), c)[0] == (h + g) % P


def test_uniform():
    u = uniform_np(np.arange(20000), 5)
    assert 0 <= u.min() and u.max() < 1 and abs(u.mean() - 0.5) < 0.01 and abs(u.var() - 1 / 12) < 0.005


def test_stable_functions(spark):
    t = [-1000.0, -1.0, 0.0, 1.0, 1000.0]
    rows = spark.createDataFrame([(v,) for v in t], "t double").select(X.sigmoid(F.col("t")).alias("s"), X.softplus(F.col("t")).alias("p")).collect()
    assert np.allclose([r["s"] for r in rows], [0, 0.26894142, 0.5, 0.73105858, 1])
    assert np.allclose([r["p"] for r in rows], [0, 0.31326169, 0.69314718, 1.31326169, 1000])
