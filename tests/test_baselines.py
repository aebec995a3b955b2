"""The averaged local Newton baselines of the workloads."""

import numpy as np

from curvetide.plans import workloads as W
from curvetide.plans.problems import Logistic
from curvetide.sources import design


def test_all_schemes_run_as_long_in_both_regimes(spark, sf):
    split = W._split(design.embeddings(spark, sf).head(6), 5)
    rows = W._second_order("x", split, Logistic(0.1), 10, 1, (12, 24, 12), 5.0, iters=3)
    last = {r[1]: r for r in rows}
    base = ["local-newton-wait-all", "local-newton-gradient-code", "local-newton-ignore", "local-newton-wait-all-damped"]
    base = [b.replace("wait-all", W.WaitAll().name) for b in base]
    assert set(last) == {"sketched-newton", "exact-newton", *base, *[b + "-published-ratio" for b in base]}
    assert all(r[2] == 3 or r[4] <= 1e-10 for r in last.values()) and all(last[b][2] == 3 for b in base)


def test_sizes_of_the_survey(spark, sf, monkeypatch):
    seen = []
    monkeypatch.setattr(W, "_second_order", lambda name, split, *a, **b: (seen.append((name, split[0].d)), [])[1])
    W.w01(spark, sf)
    W.w03(spark, f"{sf}/../sf0.1")
    assert seen == [("synthetic", 60), ("text", 300), ("text-toxic", 300)]


def test_tf_idf(spark, sf):
    a, b = (design.doc_terms(spark, sf, 20, idf=f).df.orderBy("row_id").limit(400).collect() for f in (False, True))
    n = np.array([np.square(r["x"]) for r in a])
    total, have = len(n), (n > 0).sum(axis=0)
    v = n * (np.log((1 + total) / (1 + have)) + 1)
    want = v / np.linalg.norm(v, axis=1, keepdims=True)
    assert np.allclose([r["x"] for r in b], want)
