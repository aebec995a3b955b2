import numpy as np
import pytest

from curvetide.operators import sketch as S
from curvetide.sources import design


def rows_np(d):
    r = sorted(d.df.collect(), key=lambda x: x["row_id"])
    return np.array([x["row_id"] for x in r]), np.array([x["x"] for x in r]), np.array([x["y"] for x in r])


def packed(df):
    return {(r["block"], r["bucket"]): np.frombuffer(r["v"], np.float64) for r in df.collect()}


@pytest.fixture(scope="module")
def emb(spark, sf):
    d = design.embeddings(spark, sf).head(8)
    return design.DesignMatrix(d.df.cache(), 8)


def test_sql_arrow_and_dense_agree(emb):
    s = S.BlockSketch(4, 1, 6, 3)
    ids, x, _ = rows_np(emb)
    dense = {}
    for k in range(5):
        b, sign = s.place_np(ids, k)
        for j in range(6):
            dense[k, j] = (x * sign[:, None])[b == j].sum(axis=0)
    arrow = packed(s.apply_arrow(emb.df, 8))
    assert all(np.allclose(arrow.get(k, 0), v) for k, v in dense.items())
    for r in s.apply_sql(emb.df).collect():
        assert np.isclose(dense[r["block"], r["bucket"]][r["i"]], r["v"])


def test_partitions_do_not_matter(emb):
    s = S.BlockSketch(2, 0, 4, 9)
    one, many = packed(s.apply_arrow(emb.df.repartition(1), 8)), packed(s.apply_arrow(emb.df.repartition(23), 8))
    assert one.keys() == many.keys() and all(np.allclose(one[k], many[k]) for k in one)


def test_linear(emb):
    s = S.BlockSketch(2, 0, 4, 9)
    a, b = emb.df.where("row_id < 200"), emb.df.where("row_id >= 200")
    pa, pb, pc = packed(s.apply_arrow(a, 8)), packed(s.apply_arrow(b, 8)), packed(s.apply_arrow(emb.df, 8))
    assert all(np.allclose(pa.get(k, 0) + pb.get(k, 0), v) for k, v in pc.items())


def test_gram_is_unbiased_for_any_blocks(emb):
    ids, x, _ = rows_np(emb)
    exact = x.T @ x
    total = np.zeros_like(exact)
    for seed in range(60):
        s = S.BlockSketch(3, 1, 16, seed)
        into = {k: np.zeros((16, 8)) for k in range(4)}
        s.scatter(ids, x, into, range(4))
        a = np.concatenate([into[k] for k in (0, 2, 3)])  # one block is lost
        total += a.T @ a / 3
    assert np.linalg.norm(total / 60 - exact) < 0.1 * np.linalg.norm(exact)
    assert np.allclose(S.gram_exact(emb.df, 8), exact)


def test_tiles_with_survivors(spark, emb):
    s = S.BlockSketch(3, 1, 8, 5)
    arrivals = spark.createDataFrame([(k, ci, cj, float((k * 7 + ci + 2 * cj) % 4)) for k in range(4) for ci in range(3) for cj in range(ci, 3)], "block int, ci int, cj int, t double")
    got = S.assemble(S.gram_tiles(s.apply_arrow(emb.df, 8), 8, 3, 3, arrivals).collect(), 8, 3, 3)
    ids, x, _ = rows_np(emb)
    into = {k: np.zeros((8, 8)) for k in range(4)}
    s.scatter(ids, x, into, range(4))
    want = np.zeros((8, 8))
    for i in range(8):
        for j in range(8):
            ci, cj = sorted((i // 3, j // 3))
            use = sorted(range(4), key=lambda k: ((k * 7 + ci + 2 * cj) % 4, k))[:3]
            want[i, j] = sum((into[k].T @ into[k])[i, j] for k in use) / 3
    assert np.allclose(got, want)


def test_repeated_ids_bias_the_gram_and_are_refused(spark):
    df = spark.createDataFrame([(1, 1.0, [1.0, 0.0]), (1, 1.0, [1.0, 0.0])], "row_id long, y double, x array<double>")
    with pytest.raises(ValueError, match="occurs 2 times"):
        design.DesignMatrix(df, 2).validate()
    g = S.gram_driver(S.BlockSketch(5, 0, 4, 1).apply_arrow(df, 2), 2, 5)
    assert np.isclose(g[0, 0], 4.0)  # not 2


@pytest.mark.parametrize("make", [lambda df: S.gaussian(df, 8, 800), lambda df: S.hadamard(df, 8, 64, 64)])
def test_other_embeddings(emb, make):
    _, x, _ = rows_np(emb)
    got = S.gram_driver(make(emb.df), 8, 1)
    assert np.linalg.norm(got - x.T @ x) < 0.25 * np.linalg.norm(x.T @ x)


def test_row_samples(emb):
    _, x, _ = rows_np(emb)
    for lev in (False, True):
        got = {(r["i"], r["j"]): r["h"] for r in S.gram_long(S.row_sample(emb.df, 0.7, leverage=lev)).collect()}
        assert abs(got[0, 0] / (x.T @ x)[0, 0] - 1) < 0.4


def test_plans():
    s = S.BlockSketch.of(640, 64, 0.2)
    assert (s.n, s.spare, s.width) == (10, 2, 64)
    assert S.BlockSketch.of(100, 100, spare=3).spare == 3 and s.fresh(1) != s.fresh(2) and s.grown(2).n == 20
    assert S.BlockSketch.plan(1000, 10, 24 * 250**2).width == 250
    t = S.BlockSketch.from_theory(100, 0.5)
    assert t.blocks * t.width >= 100**1.1 / 0.25


def test_scatter_equals_plain_sums():
    """Also with buckets beyond 16 bits."""
    rng = np.random.default_rng(3)
    ids, rows = rng.integers(0, 1 << 61, 700), rng.normal(size=(700, 5))
    for width in (4, 40_000):
        sk = S.BlockSketch(2, 1, width, 3)
        into = {k: np.zeros((width, 5)) for k in range(3)}
        sk.scatter(ids, rows, into, range(3))
        for k in range(3):
            bucket, sign = sk.place_np(ids, k)
            plain = np.zeros((width, 5))
            np.add.at(plain, bucket, sign[:, None] * rows)
            assert np.allclose(into[k], plain)
