"""The experiments, re-expressed on the given tables.  Each gives trace rows (workload,
scheme, it, loss, grad_norm, step, sim_s, wall_s, note, test_loss, test_error); simulated
seconds are a model.

Ratios follow the published set-ups (sketch size to features, spare blocks, workers to
rows); feature numbers are smaller."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import partial

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sketch import BlockSketch
from ..operators.vectors import packed
from ..sources import design
from ..sources.design import DesignMatrix
from ..sources.tables import trace_frame
from . import optimise as O
from .arrivals import SERVERS, ArrivalModel, GradientCode, IgnoreStragglers, Speculative, WaitAll
from .coded import CodedPair
from .measures import embedding_range
from .problems import LassoDual, LinearProgram, Logistic, Ridge, Softmax, SquaredHinge

LAM = 1e-4
LEAST, SLICE = 4 << 20, 32 << 20  # bytes of packed rows in a partition


def _held(data: DesignMatrix) -> DesignMatrix:
    return DesignMatrix(data.df.select("row_id", "y", "x").cache(), data.d, data.classes)


def _split(data: DesignMatrix, parts: int) -> tuple[DesignMatrix, DesignMatrix]:
    return tuple(_held(d) for d in data.split(parts))


def _laid(data: DesignMatrix, parts: int, workers: int) -> tuple[DesignMatrix, DesignMatrix, DataFrame]:
    """``data.split(parts)`` of rows placed for ``workers``, packed by one evaluation, and
    the persisted blocks of both.  Of rows that are drawn from their ids only these are kept,
    and each pass draws the rows block by block: they need not fit memory or disk."""
    test = F.pmod(F.xxhash64("row_id"), F.lit(parts)) == 0
    blocks = (packed(data.df.withColumn("test", test), data.d, "test") if data.drawn is None else data.ids.withColumn("test", test)).persist()
    blocks.count()
    side = lambda rows: DesignMatrix(data.df, data.d, data.classes, rows, workers, blocks.rdd.getNumPartitions(), drawn=data.drawn)
    return side(blocks.where("NOT test")), side(blocks.where("test")), blocks


def slices(nbytes: int, cores: int) -> int:
    """Partitions of packed rows: of ``LEAST`` to ``SLICE`` bytes, in whole rounds of the cores."""
    few = max(1, -(-nbytes // LEAST))
    return few if few <= cores else cores * max(1, -(-nbytes // (SLICE * cores)))


def _second_order(name, make, parts, problem, multiple, s, workers, ratio, iters=7):
    """Sketched and exact Newton and the local-averaging variants, all with as many
    iterations, with the losses and errors on held-out rows (one of ``parts`` parts).

    Averaging runs with few workers and with the published ``ratio`` of rows per worker and
    feature (but more than s workers), with unit steps and damped ones.  ``make(place)``
    gives the data; rows are laid out once, for the larger number of workers, packed and
    kept.  Fits don't depend on each other and run side by side, with shared passes."""
    plain = make(lambda rows: rows)
    cores = plain.df.sparkSession.sparkContext.defaultParallelism
    n, d = (plain if plain.ids is None else DesignMatrix(plain.ids, plain.d)).split(parts)[0].df.count(), plain.d
    many = max(s + 1, round(n / (ratio * d)))
    tasks = slices(n * d * 8, cores)
    if plain.ids is not None:  # few tasks send few partial sums, and only ids are kept
        tasks = max(min(tasks, cores), slices(n * 8, cores))
    data, test, kept = _laid(make(O.place(many, tasks)), parts, many)
    w1, w2, w3 = workers
    sk = BlockSketch.of(int(multiple * d), d, 0.2, seed=1)
    fits = [
        lambda data: O.sketched_newton(data, problem, sk, iters=iters, n_workers=w1, hess_workers=w3),
        lambda data: O.exact_newton(data, problem, iters=iters, n_workers=w1, hess_workers=w2),
    ]

    def averaged(policy, step, damped, tag, n, data):
        fit = O.averaged_local_newton(data, problem, n, policy, step, iters=iters)
        fit.scheme += damped + tag
        return fit

    for tag, k in (("", 12), ("-published-ratio", many)):
        for policy, step, damped in ((WaitAll(), None, ""), (GradientCode(s), None, ""), (IgnoreStragglers(0.9), None, ""), (WaitAll(), O.ArmijoF(), "-damped")):
            fits.append(partial(averaged, policy, step, damped, tag, k))
    done = O.side_by_side(data, fits)
    done = O.side_by_side(test, [lambda rows, fit=fit: fit.tested(rows, problem) for fit in done])
    kept.unpersist()
    return [r for fit in done for r in fit.rows(name)]


def _last(name, data: DesignMatrix, *rest):
    """``_second_order`` of data whose rows are placed when their features are there; these
    are kept meanwhile."""
    kept = data.df.persist()
    rows = _second_order(name, lambda place: DesignMatrix(place(kept), data.d, data.classes), *rest)
    kept.unpersist()
    return rows


def w01(spark, sf):
    """Synthetic logistic task, m = 10 d, gradient code s = 1."""
    return _second_order("synthetic", lambda place: design.synthetic(spark, sf, 60, place=place), 4, Logistic(LAM), 10, 1, (60, 3600, 600), 1.67)


def w02(spark, sf):
    """Dense vectors, m = 15 d, s = 3."""
    return _last("dense", design.embeddings(spark, sf), 5, Logistic(1e-2), 15, 3, (100, 10_000, 1500), 2.0)


def w03(spark, sf):
    """Sparse text by tf-idf, both targets, m = 10 d; 300 terms where there are rows for
    such a sketch, else 30."""
    d = 300 if design.tables.table(spark, sf, "labels").count() > 3000 else 30

    def run(name, target):
        return _last(name, design.doc_terms(spark, sf, d, target, idf=True), 4, Logistic(1e-2), 10, 1, (30, 900, 300), 5.5)

    with ThreadPoolExecutor(2) as pool:
        return [r for rows in pool.map(run, ("text", "text-toxic"), ("quality", "toxic")) for r in rows]


def w04(spark, sf):
    """One-hot table, m = 10 d."""
    return _second_order("table", lambda place: design.tabular(spark, sf, place=place), 3, Logistic(LAM), 10, 1, (30, 900, 300), 8.8)


def w05(spark, sf):
    """Softmax without regularisation: weakly convex; local averaging must refuse."""
    (data, test), problem = _split(design.embeddings_multi(spark, sf), 7), Softmax(10)
    fits = [
        O.exact_newton(data, problem, step=O.FixedStep(1.0), iters=5, n_workers=60, hess_workers=3600),
        O.sketched_newton(data, problem, BlockSketch.of(6 * 640, 640, 0.2, seed=2), iters=6, n_workers=60, hess_workers=360),
        O.gradient_descent(data, problem, rule=O.FixedStep(0.02), iters=10),
    ]
    rows = [r for f in fits for r in f.tested(test, problem).rows("softmax")]
    try:
        O.averaged_local_newton(data, problem)
    except ValueError as e:
        rows.append(("softmax", "local-newton", 0, float("nan"), float("nan"), 0.0, 0.0, 0.0, str(e)))
    return rows


def w06(spark, sf):
    """Coded or speculative gradients for exact and sketched Newton steps.  Coded ones come
    from the two coded rounds over data that is encoded once; speculative ones from a plain
    scan whose relaunched workers count in simulated seconds."""
    (data, test), problem, rows = _split(design.embeddings(spark, sf), 5), Logistic(1e-2), []
    pair = CodedPair.encode(data, 9, 3)
    for tag, coded in (("coded", pair), ("speculative", None)):
        for name, sk in (("exact", None), ("sketched", BlockSketch.of(15 * 64, 64, 0.2, seed=3))):
            fit = O.newton(data, problem, sketch=sk, iters=4, grad_policy=Speculative(0.9), n_workers=100, hess_workers=1500 if sk else 10_000, coded=coded)
            fit.scheme = f"{name}-{tag}"
            rows += fit.tested(test, problem).rows("coded")
    pair.release()
    return rows


def w07(spark, sf):
    """First-order methods beside a sketched Newton method."""
    (data, test), problem = _split(design.embeddings(spark, sf), 5), Logistic(1e-2)
    fits = [
        O.gradient_descent(data, problem, iters=6, policy=IgnoreStragglers(0.95)),
        O.nesterov(data, problem, iters=6, policy=IgnoreStragglers(0.95)),
        O.sgd(data, problem, iters=6),
        O.sketched_newton(data, problem, BlockSketch.of(15 * 64, 64, 0.2, seed=4), iters=5),
    ]
    return [r for f in fits for r in f.tested(test, problem).rows("first-order")]


def w08(spark, sf):
    """Sketched Newton on functions against local averaging on servers."""
    (data, test), problem = _split(design.embeddings(spark, sf), 5), Logistic(1e-2)
    a = O.sketched_newton(data, problem, BlockSketch.of(10 * 64, 64, 0.2, seed=5), iters=5, n_workers=60, hess_workers=600)
    b = O.averaged_local_newton(data, problem, 60, WaitAll(), iters=5, profile=SERVERS)
    b.scheme = "local-newton-servers"
    return a.tested(test, problem).rows("servers") + b.tested(test, problem).rows("servers")


def w09(spark, sf):
    """Job times of 3600 workers in ten trials: the median, the slow share, the longest."""
    model = ArrivalModel()
    rows = []
    for k in range(10):
        t = model.draw(3600, k)
        figures = [round(float(v), 6) for v in (np.median(t), (t > 145).mean(), t.max())]
        rows.append(("jobs", "arrivals", k, *figures, 0.0, 0.0, "loss=median grad_norm=slow share step=longest"))
    return rows


def w12(spark, sf):
    """Ridge regression; the sketch is drawn anew each iteration."""
    data = _held(design.numeric(spark, sf))
    sk = BlockSketch.of(20 * 6, 12, 0.2, seed=6)
    fits = [O.exact_newton(data, Ridge(1e-3), iters=2), O.sketched_newton(data, Ridge(1e-3), sk, iters=8)]
    fixed = O.newton(data, Ridge(1e-3), sketch=sk, iters=5, fresh=False)
    fixed.scheme = "sketched-newton-one-draw"
    return [r for f in [*fits, fixed] for r in f.rows("ridge")]


def w13(spark, sf):
    """A linear program by a barrier path, with exact and sketched inner steps."""
    data, cost = design.brand_program(spark, sf)
    data, rows = _held(data), []
    for name, sk in (("exact", None), ("sketched", BlockSketch.of(250, 25, 0.2, seed=7))):
        fit = O.barrier(data, lambda tau: LinearProgram(cost, tau), [0.3] * 25, tau=1.0, growth=20.0, stages=3, inner=5, sketch=sk)
        fit.scheme = f"barrier-{name}"
        rows += fit.rows("program")
        rows.append(("program", fit.scheme, 999, float(np.dot(cost, fit.w)), 0.0, 0.0, 0.0, 0.0, "objective"))
    return rows


def w14(spark, sf):
    """The lasso through its dual, recovered from the barrier's optimum."""
    full = design.embeddings(spark, sf)
    y = np.array(full.df.where("row_id = 0").select("x").head()[0])
    data = _held(DesignMatrix(full.df.where("row_id <> 0"), 64))
    from ..functions import columns as X

    alpha = X.dot(F.col("x"), X.weights(y.tolist()))
    bound = 0.3 * data.df.agg(F.max(F.abs(alpha))).head()[0]
    rows, start = [], np.zeros(64)
    for name, sk in (("exact", None), ("sketched", BlockSketch.of(256, 64, 0.2, seed=8))):
        fit = O.barrier(data, lambda tau: LassoDual(y, bound, tau), start, tau=10.0, growth=10.0, stages=3, inner=5, sketch=sk)
        fit.scheme = f"barrier-{name}"
        rows += fit.rows("lasso")
        gap = 0.5 * float((y - fit.w) @ (y - fit.w))
        rows.append(("lasso", fit.scheme, 999, gap, 0.0, 0.0, 0.0, 0.0, "dual distance"))
    return rows


def w15(spark, sf):
    """Sketch sizes: loss after a few steps, and the range of relative eigenvalues."""
    data, problem, rows = _held(design.synthetic(spark, sf, 12)), Logistic(LAM), []
    h = O.scan(data, problem, hessian_at=np.zeros(12)).gram
    for multiple in (2, 5, 10, 50):
        sk = BlockSketch.of(multiple * 12, 12, 0.0, seed=9)
        s = O.scan(data, problem, (), (), np.zeros(12), sk.fresh(0))
        low, high = embedding_range(h, O.sketched_hessian(s, problem, np.zeros(12), list(range(sk.blocks))))
        fit = O.sketched_newton(data, problem, sk, iters=5, guard=False)
        fit.scheme = f"m={multiple}d"
        rows += fit.rows("size") + [("size", fit.scheme, 999, low, high, 0.0, 0.0, 0.0, "eigenvalue range in loss and grad_norm")]
    return rows


def w16(spark, sf):
    """Spare blocks: simulated time to finish the same number of steps."""
    data, problem, rows = _held(design.embeddings(spark, sf)), Logistic(1e-2), []
    for zeta in (0.0, 0.1, 0.2, 0.5):
        fit = O.sketched_newton(data, problem, BlockSketch.of(10 * 64, 64, zeta, seed=10), iters=3, hess_workers=600)
        fit.scheme = f"zeta={zeta}"
        rows += fit.rows("spares")
    return rows


def svm(spark, sf):
    """Support vectors by exact and sketched Newton steps."""
    data, problem = _held(design.embeddings(spark, sf)), SquaredHinge(1e-2)
    fits = [O.exact_newton(data, problem, iters=4, step=O.ArmijoF()), O.sketched_newton(data, problem, BlockSketch.of(20 * 64, 64, 0.2, seed=12), iters=4, step=O.ArmijoF())]
    return [r for f in fits for r in f.rows("svm")]


_ALL = {f.__name__: f for f in (w01, w02, w03, w04, w05, w06, w07, w08, w09, w12, w13, w14, w15, w16, svm)}
NAMES = list(_ALL)


def run(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return trace_frame(spark, [(r[0], r[1], int(r[2]), *map(float, r[3:8]), *r[8:]) for r in _ALL[name](spark, sf_dir)])
