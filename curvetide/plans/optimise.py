"""Optimisers: sketched and exact Newton methods, first-order methods, averaged local
Newton steps; step rules; all on one scan operator."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import coefficients, hash_col, hash_np
from ..operators.sketch import BlockSketch, assemble, gram_tiles
from ..operators.vectors import collected, matrix, pack, rows_of
from ..sources.design import DesignMatrix
from ..sources.tables import load_vector, save_vector, trace_frame
from .arrivals import FUNCTIONS, AnyN, ClusterProfile, CodedGrid, GradientCode, IgnoreStragglers, Speculative, WaitAll
from .coded import CodedPair, coded_gradient, decoded
from .problems import Problem
from .solve import pinv_solve, solve_spd


@dataclass
class Scan:
    """What one pass over the data gives at a point."""

    n: float = 0.0
    losses: np.ndarray | None = None
    errors: float = float("nan")  # at the first point
    errors_at: np.ndarray | None = None
    gradients: np.ndarray | None = None
    gram: np.ndarray | None = None
    rows: np.ndarray | None = None  # sketched root rows, some of them zeros
    block_of: np.ndarray | None = None


_LOSS, _GRAD, _GRAM, _SKETCH = range(4)


def plain_or_packed(data: DesignMatrix) -> DataFrame:
    return data.blocks if data.blocks is not None else data.df.select("row_id", F.col("y").cast("double").alias("y"), "x")


class Rows:
    """A block of rows; what several requests of a pass need of it is made once."""

    def __init__(self, ids: np.ndarray, y: np.ndarray, x: np.ndarray):
        self.ids, self.y, self.x, self._of, self._cut = ids, y, x, {}, {}

    def of(self, n_workers: int) -> np.ndarray:
        if n_workers not in self._of:
            self._of[n_workers] = worker_np(self.ids, n_workers)
        return self._of[n_workers]

    def by_worker(self, n_workers: int) -> list[tuple[int, np.ndarray, np.ndarray]]:
        """(worker, x, y), cut where the worker changes."""
        if n_workers not in self._cut:
            of, y, x = self.of(n_workers), self.y, self.x
            if (of[1:] < of[:-1]).any():
                order = np.argsort(of, kind="stable")
                of, y, x = of[order], y[order], x[order]
            cut = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])).tolist() if len(of) else []
            self._cut[n_workers] = [(int(of[lo]), x[lo:hi], y[lo:hi]) for lo, hi in zip(cut, [*cut[1:], len(of)])]
        return self._cut[n_workers]


@dataclass
class Request:
    """What one fit asks of a pass: each task has an object of ``start`` for it, adds blocks
    of rows to it, and gives its rows (kind, block, bucket, v), whose v are summed by the rest."""

    start: Callable
    nbytes: int  # bound of a task's rows
    fan: int = 0
    apart: bool = False  # no two tasks give rows of the same key, so nothing is to be summed


def passed(data: DesignMatrix, requests: list[Request]) -> list[list[tuple[tuple, np.ndarray]]]:
    """The sums of each request, ((kind, block, bucket), v), by one job."""
    d, drawn, starts = data.d, data.drawn if data.blocks is not None else None, [r.start for r in requests]

    def run(batches):
        parts = [start() for start in starts]
        for block in rows_of(batches, d, drawn):
            rows = Rows(*block)
            for part in parts:
                part.add(rows)
        for i, part in enumerate(parts):
            out = part.out()
            keys = [pa.array([i] * len(out), pa.int32()), *(pa.array([o[j] for o in out], pa.int32()) for j in range(3))]
            yield pa.record_batch([*keys, pa.array([pack(o[3]) for o in out], pa.binary())], names=["request", "kind", "block", "bucket", "v"])

    sums = plain_or_packed(data).mapInArrow(run, "request int, kind int, block int, bucket int, v binary")
    nbytes = max(1, sum(r.nbytes * data.tasks for r in requests if not r.apart)) if data.tasks else 0
    found = [[] for _ in requests]
    for (i, *key), v in collected(sums, ["request", "kind", "block", "bucket"], nbytes, fan=max(r.fan for r in requests)):
        found[i].append((tuple(key), v))
    return found


class Passes:
    """Passes shared by fits that run side by side: one starts when each fit that still runs
    waits for one, and serves them all.  So fits advance together, and what a fit gets
    doesn't depend on the others."""

    def __init__(self, data: DesignMatrix, fits: int):
        self.data, self.running, self.asked, self.turn = data, fits, [], threading.Condition()

    def ask(self, request: Request) -> list:
        mine = {"request": request}
        with self.turn:
            self.asked.append(mine)
            self._go()
            while len(mine) == 1:
                self.turn.wait()
        if "error" in mine:
            raise mine["error"]
        return mine["sums"]

    def ended(self) -> None:
        with self.turn:
            self.running -= 1
            self._go()

    def _go(self) -> None:
        if not self.asked or len(self.asked) < self.running:
            return
        now, self.asked = self.asked, []
        try:
            for mine, sums in zip(now, passed(self.data, [m["request"] for m in now])):
                mine["sums"] = sums
        except Exception as e:  # each of the waiting fits raises it
            for mine in now:
                mine["error"] = e
        self.turn.notify_all()


def side_by_side(data: DesignMatrix, fits: list[Callable]) -> list:
    """The results of ``fits``, functions of the data, with shared passes."""
    passes = Passes(data, len(fits))

    def run(fit):
        try:
            return fit(replace(data, passes=passes))
        finally:
            passes.ended()

    with ThreadPoolExecutor(len(fits)) as pool:
        return list(pool.map(run, fits))


def _ask(data: DesignMatrix, request: Request) -> list:
    return passed(data, [request])[0] if data.passes is None else data.passes.ask(request)


class _ScanPart:
    def __init__(self, problem, size, at, known, grads, point, sketch, use, live):
        self.problem, self.at, self.known, self.grads, self.point, self.sketch, self.use, self.live = problem, at, known, grads, point, sketch, use, live
        self.n, self.err, self.loss = 0, np.zeros(known), np.zeros(len(at))
        self.g = np.zeros((len(grads), size))
        self.gram = np.zeros((size, size)) if point is not None and sketch is None else None
        self.into = {k: np.zeros((sketch.width, size)) for k in use} if point is not None and sketch is not None else {}

    def add(self, rows: Rows) -> None:
        ids, y, x, problem = rows.ids, rows.y, rows.x, self.problem
        if self.live is not None:
            keep = self.live[rows.of(len(self.live))]
            ids, y, x = ids[keep], y[keep], x[keep]
        self.n += len(y)
        if self.at:
            self.loss += problem.losses(x, y, self.at)
            self.err += [problem.errors(x, y, w) for w in self.at[: self.known]]
        for i, w in enumerate(self.grads):
            self.g[i] += problem.gradient(x, y, w)
        if self.point is None:
            return
        for lo in range(0, len(y), 2048):
            a = problem.root(x[lo : lo + 2048], y[lo : lo + 2048], self.point)
            if self.sketch is None:
                self.gram += a.T @ a
            else:
                k = len(a) // max(1, len(y[lo : lo + 2048]))
                key = np.repeat(ids[lo : lo + 2048], k) * k + np.tile(np.arange(k), len(ids[lo : lo + 2048])) if k > 1 else ids[lo : lo + 2048]
                self.sketch.scatter(key, a, self.into, self.use)

    def out(self) -> list[tuple]:
        out = [(_LOSS, 0, 0, np.concatenate([[self.n], self.err, self.loss]))] + [(_GRAD, i, 0, v) for i, v in enumerate(self.g)]
        if self.gram is not None:
            out.append((_GRAM, 0, 0, self.gram.reshape(-1)))
        if self.into:
            out += [(_SKETCH, k, j, v) for k, j, v in self.sketch.slabs(self.into)]
        return out


def scan(data: DesignMatrix, problem: Problem, losses_at=(), gradients_at=(), hessian_at=None, sketch: BlockSketch | None = None, blocks=None, fan: int = 0, tested: int = 1, live: np.ndarray | None = None) -> Scan:
    """One pass: losses at points, errors at the first ``tested`` of them, gradients at points, and at ``hessian_at`` the
    exact Gram matrix of the Hessian's root or its sketch.

    With ``live`` (a truth value for each worker) only the rows of these workers count.
    Points travel in the closure; partial sums leave each task once, and only vectors of
    the size of the model reach the driver."""
    size = problem.width(data.d)
    at, grads = [np.asarray(w, float) for w in losses_at], [np.asarray(w, float) for w in gradients_at]
    use = list(range(sketch.blocks)) if sketch is not None and blocks is None else list(blocks or [])
    known = min(tested, len(at))
    point = None if hessian_at is None else np.asarray(hessian_at, float)
    out = Scan(gradients=np.zeros((len(grads), size)))
    rows, of = [], []
    entries = 1 + known + len(at) + size * len(grads) + (0 if point is None else size * size if sketch is None else size * sketch.width * len(use))
    for (kind, block, _), v in _ask(data, Request(lambda: _ScanPart(problem, size, at, known, grads, point, sketch, use, live), 8 * entries, fan)):
        if kind == _LOSS:
            out.n, out.errors_at, out.losses = v[0], v[1 : 1 + known].copy(), v[1 + known :].copy()
        elif kind == _GRAD:
            out.gradients[block] = v
        elif kind == _GRAM:
            out.gram = v.reshape(size, size).copy()
        else:
            rows.append(v.reshape(-1, size))
            of.append(np.full(len(rows[-1]), block))
    if sketch is not None and point is not None:
        out.rows, out.block_of = np.concatenate([np.zeros((0, size)), *rows]), np.concatenate([np.zeros(0, int), *of])
    scale = 1.0 / max(out.n, 1) if problem.mean else 1.0
    if at:
        out.losses = out.losses * scale + [problem.reg_loss(w) for w in at]
        out.errors_at /= max(out.n, 1)
        out.errors = float(out.errors_at[0])
    for i, w in enumerate(grads):
        out.gradients[i] = out.gradients[i] * scale + problem.reg_gradient(w)
    if out.gram is not None:
        out.gram = out.gram * scale + problem.reg_hessian(point)
    return out


def sketched_hessian(s: Scan, problem: Problem, w: np.ndarray, used: list[int]) -> np.ndarray:
    a = s.rows[np.isin(s.block_of, used)]
    scale = 1.0 / max(s.n, 1) if problem.mean else 1.0
    return a.T @ a * (scale / len(used)) + problem.reg_hessian(w)


def root_rows(data: DesignMatrix, problem: Problem, w: np.ndarray) -> DataFrame:
    """(row_id, x): the rows of the Hessian's root, with ids of their own."""
    d, size = data.d, problem.width(data.d)

    def run(batches):
        for batch in batches:
            x, y, ids = matrix(batch.column("x"), d), batch.column("y").to_numpy(), batch.column("row_id").to_numpy()
            for lo in range(0, len(y), 512):
                a = problem.root(x[lo : lo + 512], y[lo : lo + 512], w)
                k = len(a) // max(1, len(y[lo : lo + 512]))
                key = np.repeat(ids[lo : lo + 512], k) * k + np.tile(np.arange(k), len(ids[lo : lo + 512])) if k > 1 else ids[lo : lo + 512]
                rows = pa.ListArray.from_arrays(pa.array(np.arange(len(a) + 1) * size, pa.int32()), pa.array(np.ascontiguousarray(a).reshape(-1)))
                yield pa.record_batch([pa.array(key), rows], names=["row_id", "x"])

    return data.df.select("row_id", F.col("y").cast("double").alias("y"), "x").mapInArrow(run, "row_id long, x array<double>")


def tiled_hessian(data: DesignMatrix, problem: Problem, w: np.ndarray, sketch: BlockSketch, used: list[int], n: float, tile: int = 256, group: int = 2) -> np.ndarray:
    """The sketched Hessian by distributed tiles: blocks are sketched ``group`` at a time, each
    tile of each block is one product, and only the summed tiles reach the driver."""
    size = problem.width(data.d)
    sketched = sketch.apply_arrow(root_rows(data, problem, w), size, blocks=used, group=group)
    h = assemble(gram_tiles(sketched, size, min(tile, size), len(used)).collect(), size, min(tile, size), len(used))
    return h * (1.0 / max(n, 1) if problem.mean else 1.0) + problem.reg_hessian(w)


# ------------------------------------------------------------------ step rules
GRID = tuple(4.0**-k for k in range(6))


@dataclass(frozen=True)
class UnitStep:
    def pick(self, ctx) -> tuple[float, bool]:
        return 1.0, False


@dataclass(frozen=True)
class FixedStep:
    alpha: float

    def pick(self, ctx):
        return self.alpha, False


@dataclass(frozen=True)
class ArmijoF:
    """The largest step of the grid with enough decrease; all losses in one pass."""

    beta: float = 0.1
    grid: tuple = GRID

    def pick(self, ctx):
        f = scan(ctx.data, ctx.problem, losses_at=[ctx.w] + [ctx.w + a * ctx.p for a in self.grid]).losses
        slope = float(ctx.p @ ctx.g)
        for a, v in zip(self.grid, f[1:]):
            if v <= f[0] + a * self.beta * slope:
                return a, False
        return self.grid[-1], True


@dataclass(frozen=True)
class ArmijoGrad:
    """Likewise on the squared gradient norm, with the approximate Hessian in the slope."""

    beta: float = 0.1
    grid: tuple = GRID

    def pick(self, ctx):
        g = scan(ctx.data, ctx.problem, gradients_at=[ctx.w + a * ctx.p for a in self.grid]).gradients
        slope, g0 = 2 * float(ctx.p @ ctx.h @ ctx.g), float(ctx.g @ ctx.g)
        for a, v in zip(self.grid, g):
            if float(v @ v) <= g0 + a * self.beta * slope:
                return a, False
        return self.grid[-1], True


@dataclass(frozen=True)
class Backtracking:
    """One pass for each trial, from ``start`` down."""

    beta: float = 0.1
    shrink: float = 0.25
    start: float = 1.0
    most: int = 12

    def pick(self, ctx):
        a, slope, f0 = self.start, float(ctx.p @ ctx.g), None
        for _ in range(self.most):
            f = scan(ctx.data, ctx.problem, losses_at=[ctx.w, ctx.w + a * ctx.p]).losses
            f0 = f[0] if f0 is None else f0
            if f[1] <= f0 + a * self.beta * slope:
                return a, False
            a *= self.shrink
        return a, True


def tune_fixed_step(data, problem, grid=(1.0, 0.5, 0.25, 0.1), run=None, iters: int = 3) -> float:
    """The step of the grid with the least loss after a few iterations."""
    run = run or (lambda a: exact_newton(data, problem, step=FixedStep(a), iters=iters))
    results = [(run(a), a) for a in grid]
    return min(results, key=lambda r: r[0].trace[-1]["loss"] if np.isfinite(r[0].trace[-1]["loss"]) else np.inf)[1]


@dataclass
class _Context:
    data: DesignMatrix
    problem: Problem
    w: np.ndarray
    p: np.ndarray
    g: np.ndarray
    h: np.ndarray | None = None


@dataclass
class FitResult:
    w: np.ndarray
    trace: list[dict] = field(default_factory=list)
    scheme: str = ""

    @property
    def loss(self) -> float:
        return self.trace[-1]["loss"]

    def save(self, spark, path: str) -> None:
        """Weights and trace, to go on from later."""
        save_vector(spark, self.w, f"{path}/w")
        trace_frame(spark, self.rows("")).write.mode("overwrite").parquet(f"{path}/trace")

    @staticmethod
    def find(spark, path: str) -> FitResult | None:
        """A saved fit, or None where there is none."""
        there = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/trace/_SUCCESS")
        if not there.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(there):
            return None
        return FitResult.load(spark, path)

    @staticmethod
    def load(spark, path: str) -> FitResult:
        rows = spark.read.parquet(f"{path}/trace").orderBy("it").collect()
        keys = ("it", "loss", "grad_norm", "step", "sim_s", "wall_s", "note", "test_loss", "test_error")
        return FitResult(load_vector(spark, f"{path}/w"), [{k: r[k] for k in keys} for r in rows], rows[0]["scheme"] if rows else "")

    def rows(self, workload: str) -> list[tuple]:
        return [(workload, self.scheme, t["it"], float(t["loss"]), float(t["grad_norm"]), float(t["step"]), float(t["sim_s"]), float(t["wall_s"]), t["note"], t.get("test_loss"), t.get("test_error")) for t in self.trace]

    def tested(self, data: DesignMatrix, problem: Problem) -> FitResult:
        """Adds loss and error rate on held-out rows to the trace: one scan for all its
        points.  Points at which the fit diverged are left out."""
        live = [t for t in self.trace if "w" in t and np.isfinite(t["w"]).all()]
        if live:
            s = scan(data, problem, [t["w"] for t in live], tested=len(live))
            for t, loss, error in zip(live, s.losses, s.errors_at):
                t["test_loss"], t["test_error"] = float(loss), float(error)
        return self


class _Run:
    """Keeps the trace of a fit."""

    def __init__(self, scheme: str, w0: np.ndarray, profile: ClusterProfile):
        self.out, self.sim, self.began, self.profile = FitResult(w0, [], scheme), 0.0, time.time(), profile

    def log(self, it, w, loss, g, step, note="") -> None:
        self.out.w = w
        self.out.trace.append({"it": it, "loss": loss, "grad_norm": float(np.linalg.norm(g)), "step": step, "sim_s": self.sim, "wall_s": time.time() - self.began, "note": note, "w": w})


# ------------------------------------------------------------------ Newton methods
def newton(data: DesignMatrix, problem: Problem, w0=None, sketch: BlockSketch | None = None, step=None, iters: int = 8, tol: float = 1e-10, rcond: float = 1e-8, grad_policy=None, hess_policy=None, profile: ClusterProfile = FUNCTIONS, n_workers: int = 60, hess_workers: int | None = None, schedule=None, guard: bool = True, fresh: bool = True, coded: CodedPair | None = None, fan: int = 0, driver_bytes: int = 256 << 20, path: str | None = None) -> FitResult:
    """Newton steps with the exact Hessian (``sketch`` None) or a sketched one.

    The gradient is exact.  Of the sketch's N + e blocks the first N to arrive in the
    simulated round are used.  Weakly convex problems take the pseudo-inverse and the
    gradient-norm rule.  A sketch is drawn anew each iteration (``fresh``); ``schedule``
    maps the iteration to a growth factor.  With ``guard`` two rises of the loss in a row
    switch unit steps to a line search.  With ``coded`` losses, gradients and sketches come
    from the two coded rounds over the encoded data, whose waiting times count.  Sketches of
    over ``driver_bytes`` aren't collected: their Gram matrix is summed by distributed tiles.
    With ``path`` weights and trace are saved after each iteration, and a fit that finds them
    there goes on from the last one, with the draws that the whole fit has."""
    weak = problem.convexity == "weak"
    step = step or (ArmijoGrad() if weak else UnitStep())
    grad_policy = grad_policy or (CodedGrid() if sketch else Speculative())
    hess_workers = hess_workers or n_workers
    w = np.zeros(problem.width(data.d)) if w0 is None else np.asarray(w0, float)
    run, rises, last, first = _Run("sketched-newton" if sketch else "exact-newton", w, profile), 0, np.inf, 0
    spark = data.df.sparkSession
    if path and (old := FitResult.find(spark, path)) is not None:
        w, first = old.w, old.trace[-1]["it"]
        run.out.trace = old.trace[:-1]
        run.sim = run.out.trace[-1]["sim_s"] if run.out.trace else 0.0
    for it in range(first, iters + 1):
        if path and it > first:
            run.out.save(spark, path)
        now = None
        if sketch is not None:
            now = sketch.fresh(it) if fresh else sketch
            now = now.grown(schedule(it)) if schedule else now
        large = now is not None and 8 * now.blocks * now.width * len(w) > driver_bytes
        ride = None if large or it == iters else now
        if coded is not None:
            r = coded.evaluate(problem, w, it, profile.model, ride, fan=fan)
            s = Scan(r.n, np.array([r.loss]), gradients=r.gradient[None], rows=r.rows, block_of=r.block_of)
            if sketch is None and it < iters:
                s.gram = scan(data, problem, hessian_at=w, fan=fan).gram
        else:
            s = scan(data, problem, [w], [w], w if it < iters and not large else None, ride, fan=fan)
        g, loss = s.gradients[0], s.losses[0]
        rises = rises + 1 if loss > last else 0
        last = loss
        if it == iters or float(np.linalg.norm(g)) <= tol or not np.isfinite(loss):
            run.log(it, w, loss, g, 0.0, "" if np.isfinite(loss) else "diverged")
            break
        if sketch is None:
            h, policy = s.gram, hess_policy or Speculative()
        else:
            t = profile.model.draw(now.blocks, it, 5)
            used = sorted(np.argsort(t, kind="stable")[: now.n].tolist())
            h = tiled_hessian(data, problem, w, now, used, s.n) if large else sketched_hessian(s, problem, w, used)
            policy = hess_policy or AnyN(now.n, now.spare)
        p = -(pinv_solve(h, g, rcond) if weak else solve_spd(h, g))
        if coded is not None:
            run.sim += sum(profile.start + profile.unit * t for t in r.waited) + profile.per_gb * 8 * len(w) * n_workers / 1e9
        else:
            run.sim += profile.round(grad_policy, n_workers, it, 0, 8 * len(w) * n_workers) + profile.round(grad_policy, n_workers, it, 1)
        run.sim += profile.round(policy, hess_workers, it, 2, 8 * len(w) ** 2)
        note = ""
        rule = step
        if guard and rises >= 2 and isinstance(step, UnitStep):
            rule, note = ArmijoF(), "guard"
        alpha, failed = rule.pick(_Context(data, problem, w, p, g, h))
        if not isinstance(rule, (UnitStep, FixedStep)):
            run.sim += profile.round(grad_policy, n_workers, it, 3)
        run.log(it, w, loss, g, alpha, "ls_failed" if failed else note)
        w = w + alpha * p
    if path:
        run.out.save(spark, path)
    return run.out


def exact_newton(data, problem, **kw) -> FitResult:
    return newton(data, problem, sketch=None, **kw)


def sketched_newton(data, problem, sketch: BlockSketch, **kw) -> FitResult:
    return newton(data, problem, sketch=sketch, **kw)


# ------------------------------------------------------------------ first-order methods
def _survivors(data: DesignMatrix, policy, n_workers: int, profile, it: int) -> DesignMatrix:
    """The rows of the workers that aren't ignored this round."""
    if not isinstance(policy, IgnoreStragglers):
        return data
    keep = policy.survivors(profile.model.draw(n_workers, it, 0))
    live = [int(i) for i in np.flatnonzero(keep)]
    return DesignMatrix(data.df.where(_worker(n_workers).isin(live)), data.d, data.classes)


def first_order(data, problem, w0=None, momentum: bool = False, fraction: float = 1.0, policy=None, rule=None, start: float = 64.0, iters: int = 20, profile: ClusterProfile = FUNCTIONS, n_workers: int = 60, scheme: str = "") -> FitResult:
    """Gradient descent; with ``momentum`` Nesterov's accelerated method; with ``fraction``
    below 1 on a hash-drawn minibatch of that share each iteration.  The default rule takes
    the step that backtracking from ``start`` would find, with all trials in one pass."""
    policy = policy or WaitAll()
    rule = rule or ArmijoF(grid=tuple(start * 0.25**k for k in range(12)))
    w = np.zeros(problem.width(data.d)) if w0 is None else np.asarray(w0, float)
    run, prev, t = _Run(scheme or ("nesterov" if momentum else "gradient-descent"), w, profile), w, 1.0
    for it in range(iters + 1):
        t_next = (1 + np.sqrt(1 + 4 * t * t)) / 2
        v = w + (t - 1) / t_next * (w - prev) if momentum else w
        full = scan(data, problem, [w], [w] if v is w else [w, v])
        if it == iters:
            run.log(it, w, full.losses[0], full.gradients[0], 0.0)
            break
        part = _survivors(data, policy, n_workers, profile, it)
        if fraction < 1:
            u = hash_col(F.col("row_id"), coefficients(701, it)) / 2147483647.0
            part = DesignMatrix(part.df.where(u < fraction), data.d, data.classes)
        g = full.gradients[-1] if part is data else scan(part, problem, (), [v]).gradients[0]
        alpha, failed = rule.pick(_Context(part, problem, v, -g, g))
        run.sim += profile.round(policy, n_workers, it, 0, 8 * len(w) * n_workers, work=fraction)
        if not isinstance(rule, FixedStep):
            run.sim += 0.15 * profile.round(policy, n_workers, it, 3, work=fraction)
        run.log(it, w, full.losses[0], full.gradients[0], alpha, "ls_failed" if failed else "")
        prev, w, t = w, v - alpha * g, t_next
    return run.out


def gradient_descent(data, problem, **kw) -> FitResult:
    return first_order(data, problem, **kw)


def nesterov(data, problem, **kw) -> FitResult:
    return first_order(data, problem, momentum=True, **kw)


def sgd(data, problem, fraction: float = 0.2, **kw) -> FitResult:
    return first_order(data, problem, fraction=fraction, scheme="sgd", **kw)


# ------------------------------------------------------------------ averaged local Newton
def _worker(n_workers: int):
    return F.pmod(hash_col(F.col("row_id"), coefficients(97)), F.lit(n_workers)).cast("int")


def worker_np(ids: np.ndarray, n_workers: int) -> np.ndarray:
    """As ``_worker``, of row ids."""
    return hash_np(ids, coefficients(97)) % n_workers


def place(n_workers: int, parts: int):
    """Rows (row_id, ...) of a worker one behind the other in one of ``parts`` partitions."""
    return lambda rows: rows.repartition(parts, _worker(n_workers)).sortWithinPartitions(_worker(n_workers))


def _direction(problem: Problem, w, g, n: int, h: np.ndarray, n_workers: int) -> np.ndarray:
    full = h * (1 / n if problem.mean else float(n_workers)) + problem.reg_hessian(w)
    return -solve_spd(full + 1e-12 * np.eye(len(w)), g)


class _WorkerSums:
    """(0, worker, 0, v): the number of rows of each worker and the sum of a function of them.
    With ``apart`` v has a line (worker, number, sum) for each of about a megabyte of a
    task's workers, as rows for many workers cost more than their sums."""

    def __init__(self, of, n_workers: int, live: np.ndarray | None = None, apart: bool = False):
        self.of, self.n_workers, self.live, self.apart, self.total = of, n_workers, live, apart, {}

    def add(self, rows: Rows) -> None:
        for k, x, y in rows.by_worker(self.n_workers):
            if self.live is None or self.live[k]:
                n, v = self.total.get(k, (0, 0.0))
                self.total[k] = (n + len(y), v + self.of(x, y))

    def out(self) -> list[tuple]:
        if not self.apart:
            return [(0, k, 0, np.concatenate([[n], v.reshape(-1)])) for k, (n, v) in self.total.items()]
        lines, out = list(self.total.items()), []
        step = max(1, (1 << 20) // (8 * (2 + np.size(lines[0][1][1])))) if lines else 1
        for lo in range(0, len(lines), step):
            out.append((0, lines[lo][0], 0, np.concatenate([np.concatenate([[k, n], v.reshape(-1)]) for k, (n, v) in lines[lo : lo + step]])))
        return out


class _Directions:
    """(0, 0, 0, v): the number of workers whose rows lie in a task, and the sum of their
    directions; holds one Hessian at a time."""

    def __init__(self, problem, w, g, n_workers: int, live: np.ndarray | None):
        self.problem, self.w, self.g, self.n_workers, self.live = problem, w, g, n_workers, live
        self.now, self.n, self.h, self.sum = None, 0, None, np.zeros(1 + len(w))

    def add(self, rows: Rows) -> None:
        for k, x, y in rows.by_worker(self.n_workers):
            if self.live is None or self.live[k]:
                if k != self.now:
                    self.finish()
                    self.now, self.n, self.h = k, 0, 0.0
                a = self.problem.root(x, y, self.w)
                self.n, self.h = self.n + len(y), self.h + a.T @ a

    def finish(self) -> None:
        if self.now is not None:
            self.sum += np.concatenate([[1.0], _direction(self.problem, self.w, self.g, self.n, self.h, self.n_workers)])

    def out(self) -> list[tuple]:
        self.finish()
        return [(0, 0, 0, self.sum)]


def packed_gradient(data: DesignMatrix, problem: Problem, w: np.ndarray, n_workers: int, s: int, times: np.ndarray) -> np.ndarray:
    """``coded_gradient`` of packed blocks.  Where rows lie by worker a worker's gradient is
    complete when it leaves its task; else the tasks' partial ones are summed."""
    parts, n, apart = np.zeros((n_workers, problem.width(data.d))), 0.0, data.laid == n_workers
    request = Request(lambda: _WorkerSums(lambda x, y: problem.gradient(x, y, w), n_workers, apart=apart), 8 * n_workers * (1 + len(w)), apart=apart)
    for (_, k, _), v in _ask(data, request):
        if apart:
            v = v.reshape(-1, 2 + len(w))
            parts[v[:, 0].astype(int)], n = v[:, 2:], n + v[:, 1].sum()
        else:
            parts[k], n = v[1:], n + v[0]
    return decoded(parts, n, problem, w, s, times)


def _outer(problem: Problem, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    a = problem.root(x, y, w)
    return a.T @ a


def packed_direction(data: DesignMatrix, problem: Problem, w: np.ndarray, g: np.ndarray, n_workers: int, live: np.ndarray | None = None) -> np.ndarray:
    """The mean of the workers' directions (see ``local_directions``) from packed blocks.

    Where rows lie by worker a task holds one Hessian at a time, and the sum of its
    directions leaves it.  Else a task holds those of all workers, which are summed and
    solved at the driver: for few workers."""
    size = problem.width(data.d)
    if data.laid == n_workers:
        total = _ask(data, Request(lambda: _Directions(problem, w, g, n_workers, live), 8 * (1 + size)))[0][1]
        return total[1:] / total[0]
    if 8 * n_workers * size * size > 64 << 20:
        raise ValueError("rows must be laid out for so many workers")
    request = Request(lambda: _WorkerSums(lambda x, y: _outer(problem, w, x, y), n_workers, live), 8 * n_workers * (1 + size * size))
    each = [v for _, v in sorted(_ask(data, request), key=lambda r: r[0])]
    return np.mean([_direction(problem, w, g, int(v[0]), v[1:].reshape(size, size), n_workers) for v in each], axis=0)


def by_worker(data: DesignMatrix, n_workers: int) -> DataFrame:
    """(worker, y, x) with the rows of a worker one behind the other in one partition; laid
    out once for all iterations."""
    rows = data.df.select(_worker(n_workers).alias("worker"), F.col("y").cast("double").alias("y"), "x")
    return rows.repartition("worker").sortWithinPartitions("worker")


def local_directions(laid: DataFrame, d: int, problem: Problem, w: np.ndarray, g: np.ndarray, n_workers: int) -> DataFrame:
    """(worker, n, v packed): the solution of each worker's own Hessian for the gradient, from
    rows as ``by_worker`` lays them.  Hessians are summed as the rows stream by; a task holds
    one at a time."""
    size = problem.width(d)

    def solve(batches):
        now, n, h = None, 0, None

        def finish():
            full = h * (1 / n if problem.mean else float(n_workers)) + problem.reg_hessian(w)
            return pa.record_batch([pa.array([now], pa.int32()), pa.array([n], pa.int64()), pa.array([pack(-solve_spd(full + 1e-12 * np.eye(size), g))], pa.binary())], names=["worker", "n", "v"])

        for batch in batches:
            x, y, of = matrix(batch.column("x"), d), batch.column("y").to_numpy(), batch.column("worker").to_numpy()
            cut = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])) if len(of) else []
            for lo, hi in zip(cut, [*cut[1:], len(of)]):
                if of[lo] != now:
                    if now is not None:
                        yield finish()
                    now, n, h = int(of[lo]), 0, np.zeros((size, size))
                a = problem.root(x[lo:hi], y[lo:hi], w)
                n, h = n + int(hi - lo), h + a.T @ a
        if now is not None:
            yield finish()

    return laid.mapInArrow(solve, "worker int, n long, v binary")


def averaged_local_newton(data, problem, n_workers: int = 60, policy=None, step=None, iters: int = 8, w0=None, profile: ClusterProfile = FUNCTIONS) -> FitResult:
    """Two rounds an iteration: the full gradient, then the mean of local Newton steps.

    Policies: wait for all, ignore stragglers in both rounds, or a gradient code for the
    first: the exact gradient is decoded from the messages of all workers but the s slowest,
    at s + 1 times the work.  Rows are laid out by worker once."""
    if problem.convexity == "weak":
        raise ValueError("averaging local Newton steps needs a strongly convex problem")
    policy, step = policy or WaitAll(), step or UnitStep()
    w = np.zeros(problem.width(data.d)) if w0 is None else np.asarray(w0, float)
    run = _Run(f"local-newton-{policy.name}", w, profile)
    laid = by_worker(data, n_workers).persist() if data.blocks is None else None
    for it in range(iters + 1):
        full = scan(data, problem, [w], [w])
        if it == iters or not np.isfinite(full.losses[0]):
            run.log(it, w, full.losses[0], full.gradients[0], 0.0, "" if np.isfinite(full.losses[0]) else "diverged")
            break
        part, kept = data if laid is None else _survivors(data, policy, n_workers, profile, it), laid
        if laid is None:
            live = policy.survivors(profile.model.draw(n_workers, it, 0)) if isinstance(policy, IgnoreStragglers) else None
            if isinstance(policy, GradientCode):
                g = packed_gradient(data, problem, w, n_workers, policy.s, profile.model.draw(n_workers, it, 0))
            else:
                g = full.gradients[0] if live is None else scan(data, problem, (), [w], live=live).gradients[0]
            p = packed_direction(data, problem, w, g, n_workers, live)
        elif part is not data:
            live = np.flatnonzero(policy.survivors(profile.model.draw(n_workers, it, 0))).tolist()
            kept = laid.where(F.col("worker").isin(live))
        if laid is not None:
            if isinstance(policy, GradientCode):
                g = coded_gradient(data, problem, w, n_workers, policy.s, _worker(n_workers), profile.model.draw(n_workers, it, 0))
            else:
                g = full.gradients[0] if part is data else scan(part, problem, (), [w]).gradients[0]
            rows = local_directions(kept, data.d, problem, w, g, n_workers).collect()
            p = np.mean([np.frombuffer(r["v"], np.float64) for r in rows], axis=0)
        alpha, failed = step.pick(_Context(data, problem, w, p, g))
        second = WaitAll() if isinstance(policy, GradientCode) else policy
        run.sim += profile.round(policy, n_workers, it, 0, 8 * len(w) * n_workers) + profile.round(second, n_workers, it, 2, 8 * len(w) * n_workers)
        run.log(it, w, full.losses[0], full.gradients[0], alpha, "ls_failed" if failed else "")
        w = w + alpha * p
    if laid is not None:
        laid.unpersist()
    return run.out


# ------------------------------------------------------------------ barrier methods
def barrier(data: DesignMatrix, make, x0, tau: float = 1.0, growth: float = 10.0, stages: int = 6, inner: int = 10, sketch: BlockSketch | None = None, tol: float = 1e-8) -> FitResult:
    """A path of barrier problems ``make(tau)``; each starts where the last one ended.  The
    start must be strictly feasible."""
    w, out = np.asarray(x0, float), FitResult(np.asarray(x0, float), [], "barrier")
    if not np.isfinite(scan(data, make(tau), [w]).losses[0]):
        raise ValueError("the start isn't strictly feasible")
    for k in range(stages):
        problem = make(tau)
        grown = BlockSketch(sketch.n, sketch.spare, sketch.width, sketch.seed + 100 * k) if sketch else None
        fit = newton(data, problem, w, sketch=grown, step=ArmijoF(grid=tuple(4.0**-j for j in range(10))), iters=inner, tol=tol * tau, guard=False)
        w = fit.w
        out.trace += [{**t, "it": len(out.trace) + i, "note": f"tau={tau:g}"} for i, t in enumerate(fit.trace)]
        tau *= growth
    out.w = w
    return out
