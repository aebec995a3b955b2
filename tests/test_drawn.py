"""Rows that are functions of their ids are drawn in each pass; only the ids are kept."""

import numpy as np
import pytest

from curvetide.functions.hashing import P as PRIME
from curvetide.functions.hashing import coefficients, hash_np, hash_of, powers
from curvetide.operators.sketch import BlockSketch
from curvetide.operators.vectors import packed, rows_of
from curvetide.plans import optimise as O
from curvetide.plans import workloads
from curvetide.plans.arrivals import GradientCode, IgnoreStragglers
from curvetide.plans.problems import Logistic
from curvetide.sources import design
from curvetide.sources.design import DesignMatrix

P = Logistic(1e-2)


@pytest.fixture(scope="module")
def both(spark, sf):
    """Packed rows, and the train part of drawn ones; both laid out for 40 workers."""
    data = design.synthetic(spark, sf, 12, place=O.place(40, 3))
    train, test, kept = workloads._laid(data, 4, 40)
    plain = DesignMatrix(data.df, 12).split(4)[0]
    yield DesignMatrix(plain.df, 12, 0, packed(plain.df, 12).persist(), 40, 3), train, kept
    kept.unpersist()


def test_only_ids_are_kept(both):
    """Twelve doubles a row and more were kept, with which a cluster's memory and disk filled."""
    assert dict(both[2].dtypes) == {"row_id": "bigint", "test": "boolean"} and both[2].is_cached


def test_drawn_passes_equal_packed_ones(both):
    w, sk = np.linspace(-0.3, 0.3, 12), BlockSketch.of(120, 12, 0.2, seed=1)
    a, b = (O.scan(d, P, [w], [w], w, sk) for d in both[:2])
    assert a.n == b.n and a.errors == b.errors and np.allclose(a.losses, b.losses) and np.allclose(a.gradients, b.gradients)
    assert np.allclose(O.sketched_hessian(a, P, w, [0, 1, 2]), O.sketched_hessian(b, P, w, [0, 1, 2]))
    for workers in (40, 7):
        for policy in (GradientCode(2), IgnoreStragglers(0.8)):
            a, b = (O.averaged_local_newton(d, P, workers, policy, iters=2) for d in both[:2])
            assert np.allclose(a.w, b.w, rtol=1e-9, atol=1e-12)


def test_gradients_of_many_workers_leave_a_task_in_few_rows():
    part = O._WorkerSums(lambda x, y: P.gradient(x, y, np.zeros(3)), 5000, apart=True)
    ids = np.arange(60_000)
    part.add(O.Rows(ids, np.ones(len(ids)), np.ones((len(ids), 3))))
    out = part.out()
    lines = np.concatenate([v for *_, v in out]).reshape(-1, 5)
    assert len(out) == 1 and len(lines) == len(np.unique(O.worker_np(ids, 5000))) and lines[:, 1].sum() == len(ids)
    assert O._WorkerSums(len, 5, apart=True).out() == []


def test_rows_are_drawn_a_megabyte_at_a_time(spark, sf):
    data = design.synthetic(spark, sf, 60)
    ids = data.ids.limit(5000).toArrow().to_batches()
    blocks = list(rows_of(ids, 60, data.drawn))
    assert max(x.nbytes for _, _, x in blocks) <= 1 << 20 and sum(len(i) for i, _, _ in blocks) == 5000


def test_a_pass_has_few_partial_sums(spark, sf, monkeypatch):
    """Partitions go by the bytes of the ids and not of the rows."""
    seen, laid = [], O.place
    monkeypatch.setattr(O, "place", lambda workers, parts: (seen.append(parts), laid(workers, parts))[1])
    monkeypatch.setattr(workloads, "LEAST", 1 << 14)
    monkeypatch.setattr(workloads, "SLICE", 1 << 14)
    monkeypatch.setattr(O, "side_by_side", lambda data, fits: [])
    workloads._second_order("t", lambda place: design.synthetic(spark, sf, 60, place=place), 4, P, 10, 1, (60, 3600, 600), 1.67)
    assert seen == [spark.sparkContext.defaultParallelism]


def test_hash_of_powers():
    ids = np.array([0, 1, PRIME - 1, PRIME, PRIME + 1, 2 * PRIME, PRIME * PRIME - 1, PRIME * PRIME, (1 << 61) - 1, -1, -PRIME - 1, -(1 << 61)])
    for some in (ids, ids[:3], ids[:0], np.random.default_rng(0).integers(0, 1 << 61, 10_000)):
        for coef in [coefficients(k, 3 * k) for k in range(20)] + [(PRIME - 1,) * 7]:
            assert (hash_of(powers(some), coef) == hash_np(some, coef)).all()
