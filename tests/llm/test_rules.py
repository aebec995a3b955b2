import collections
import random
import re

import numpy as np

from curvetide.llm import quality_rules as Q

SCHEMA = "doc_id long, text string, lang string, source string, kept string"


def base(t):
    t = t or ""
    w = t.encode().split()
    lines = [x for x in t.split("\n") if x.encode().split()]
    g = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    c = collections.Counter(g)
    cover = {k for i, x in enumerate(g) if c[x] > 1 for k in range(i, i + 5)}
    return len(w), sum(len(x.decode()) for x in w), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover)


def corpus(spark, n=600):
    rng = random.Random(3)
    vocab = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 9))) for _ in range(4000)]
    rows = []
    for i in range(n):
        words = [rng.choice(vocab) for _ in range(rng.randint(30, 300))]
        if i % 10 == 0:
            words = [w + "%%%" for w in words]
        rows.append((i, "\n".join(" ".join(words[k : k + 9]) for k in range(0, len(words), 9)), "en" if i % 3 else None, "hot" if i % 4 else f"s{i % 8}", "k"))
    rows += [(1000, None, "en", "hot", None), (1001, "", None, None, None), (1002, "a b c d e " * 30, "en", "hot", None), (1003, "x\ny\nx\n \n\t\nx", "en", "hot", None), (1004, "one two three", "zz", "rare", None), (5, rows[5][1], rows[5][2], rows[5][3], None), (None, rows[7][1], "en", "hot", None), (1005, "a\x1cb c #\r\n" * 20, "en", "hot", None)]
    return rows, spark.createDataFrame(rows, SCHEMA)


def test_base_columns(spark):
    rows, df = corpus(spark)
    got = sorted(((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) for r in Q.judge(df).collect()), key=str)
    want = []
    for i, t, *_ in rows:
        b = base(t)
        want.append((i, *b, b[0] < 10 or 100 * b[4] > 20 * b[0]))
    assert got == sorted(want, key=str)


def test_outliers_go_and_clean_rows_stay(spark):
    _, df = corpus(spark)
    rows = Q.judge(df).collect()
    for r in rows:
        if r["doc_id"] is not None and r["doc_id"] < 600:
            assert r["kept"] == (r["doc_id"] % 10 != 0), r
    kept = Q.keep_good(df)
    assert kept.columns == df.columns and kept.count() == sum(r["kept"] for r in rows)


FRAME = "grp string, " + ", ".join(f"x{i} double" for i in range(5))


def least_determinant(x, h, starts=60):
    """Concentration steps over rows from many random starts, in NumPy."""
    rng, floor, best = np.random.default_rng(5), np.diag(np.square(Q.FLOOR)), None
    for k in range(starts):
        near = x[rng.choice(len(x), 8 if k else len(x), replace=False)]
        was = np.inf
        while True:
            m, c = near.mean(axis=0), Q.CONSISTENT * np.cov(near.T, bias=True) + floor
            det = np.linalg.slogdet(c)[1]
            if len(near) == h and det >= was - 1e-12:
                break
            was = det if len(near) == h else np.inf
            d = np.einsum("ij,jk,ik->i", x - m, np.linalg.inv(c), x - m)
            near = x[np.argsort(d, kind="stable")[:h]]
        if best is None or det < best[0]:
            best = det, m, c
    return best


def test_estimates_against_numpy(spark, monkeypatch):
    """The determinant found is the least that many random starts find over single rows, but
    for what the grid takes together."""
    rng = np.random.default_rng(0)
    turn = np.linalg.qr(rng.normal(size=(5, 5)))[0] * [1.0, 0.5, 0.8, 0.3, 0.6]
    x = np.concatenate([rng.normal(size=(700, 5)) @ turn.T, rng.normal(scale=0.2, size=(150, 5)) + 4])
    y = rng.normal(size=(300, 5)) + 2
    monkeypatch.setattr(Q, "LIMITS", ((-12, 12),) * 5)
    df = spark.createDataFrame([("g", *map(float, v)) for v in x] + [("k", *map(float, v)) for v in y], FRAME)
    got = {r["grp"]: r for r in Q.fit(df).collect()}
    for grp, data in (("g", x), ("k", y)):
        det, m, c = least_determinant(data, int(np.ceil(Q.NEAR * len(data))))
        low = np.array([[got[grp][f"l{i}{j}"] if j <= i else 0.0 for j in range(5)] for i in range(5)])
        assert abs(got[grp]["det"] - det) < 0.05 and np.allclose(got[grp]["det"], np.linalg.slogdet(low @ low.T)[1])
        assert np.allclose([got[grp][f"m{i}"] for i in range(5)], m, atol=0.08) and np.allclose(low @ low.T, c, atol=0.12)
    assert np.abs([got["g"][f"m{i}"] for i in range(5)]).max() < 0.2  # the far rows have no part


def test_a_grid_adds_up_and_is_bounded(spark):
    rng = np.random.default_rng(1)
    x = np.abs(rng.normal(scale=0.08, size=(4000, 5)))
    x[0] = [1e6, -1e6, 99, 99, 99]
    df = spark.createDataFrame([("hot", *map(float, v)) for v in x], FRAME)
    grid = Q.cells(df).collect()
    assert sum(r["n"] for r in grid) == 4000 and len(grid) < 2000
    total = x.T @ x
    assert all(np.isclose(sum(r[f"q{i}{j}"] for r in grid), total[i, j]) for i, j in Q._PAIRS)
    assert len(Q.cells(df.union(df)).collect()) == len(grid)


def test_chi_squared():
    known = ((0.05, 1, 3.8415), (0.5, 4, 3.3567), (0.001, 5, 20.515), (0.05, 10, 18.307))
    for tail, df, x in known:
        assert abs(Q.chi2_quantile(tail, df) - x) < 1e-3 and abs(Q.chi2_tail(x, df) - tail) < 1e-4


def test_many_duplicate_lines(spark):
    rng = random.Random(11)
    vocab = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 9))) for _ in range(4000)]
    line = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    rows = [(i, "\n".join(line(9) for _ in range(rng.randint(4, 30))), "en", "s", None) for i in range(300)]
    rows.append((999, "\n".join(x for _ in range(25) for x in (line(9), "read more here")), "en", "s", None))
    got = {r["doc_id"]: r for r in Q.judge(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert not got[999]["base_failed"] and got[999]["n_repeat_words"] == 0 and not got[999]["kept"]
    assert sum(r["kept"] for r in got.values()) >= 298


def test_no_python_in_the_plan(spark):
    _, df = corpus(spark, 100)
    plan = Q.judge(df)._jdf.queryExecution().toString() + Q.statistics(df)._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_empty_table(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert Q.judge(empty).count() == 0 and Q.keep_good(empty).columns == empty.columns
