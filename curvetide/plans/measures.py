"""Cost and accuracy measures on traces and Hessians."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


# ------------------------------------------------------------------ traces
def time_to_target(trace: DataFrame, target: float, clock: str = "sim_s") -> DataFrame:
    """(workload, scheme, t): the first clock value at which the loss is at most target."""
    return trace.where(F.col("loss") <= target).groupBy("workload", "scheme").agg(F.min(clock).alias("t"))


def iters_to_target(trace: DataFrame, target: float) -> DataFrame:
    return trace.where(F.col("loss") <= target).groupBy("workload", "scheme").agg(F.min("it").alias("iters"))


def speed_up(times: DataFrame, base: str) -> DataFrame:
    """Share of time that each scheme saves against ``base``."""
    ref = times.where(F.col("scheme") == base).select("workload", F.col("t").alias("t0"))
    return times.join(ref, "workload").select("workload", "scheme", (1 - F.col("t") / F.col("t0")).alias("saved"))


def contraction(trace: DataFrame, optimum: float) -> DataFrame:
    """Ratios of successive loss gaps, and their logs' ratio (2 when quadratic)."""
    w = Window.partitionBy("workload", "scheme").orderBy("it")
    gap = F.col("loss") - optimum
    rows = trace.withColumn("gap", gap).withColumn("before", F.lag("gap").over(w))
    return rows.where("before > 0 AND gap > 0").select("workload", "scheme", "it", (F.col("gap") / F.col("before")).alias("ratio"), (F.log("gap") / F.log("before")).alias("order"))


def best_so_far(trace: DataFrame) -> DataFrame:
    w = Window.partitionBy("workload", "scheme").orderBy("it").rowsBetween(Window.unboundedPreceding, 0)
    return trace.withColumn("best", F.min("loss").over(w))


def phase_share(rounds: DataFrame) -> DataFrame:
    """(scheme, phase, share) of (scheme, phase, s)."""
    total = Window.partitionBy("scheme")
    return rounds.groupBy("scheme", "phase").agg(F.sum("s").alias("s")).select("scheme", "phase", (F.col("s") / F.sum("s").over(total)).alias("share"))


def aligned(trace: DataFrame, grid: DataFrame, clock: str = "sim_s") -> DataFrame:
    """(scheme, t, loss): each scheme's last loss at or before each time of the grid, by a
    union with the grid and a running last value."""
    points = trace.select("scheme", F.col(clock).alias("t"), "loss", F.lit(0).alias("g"))
    asked = trace.select("scheme").distinct().crossJoin(F.broadcast(grid.select("t"))).select("scheme", "t", F.lit(None).cast("double").alias("loss"), F.lit(1).alias("g"))
    w = Window.partitionBy("scheme").orderBy("t", "g").rowsBetween(Window.unboundedPreceding, 0)
    return points.unionByName(asked).withColumn("loss", F.last("loss", ignorenulls=True).over(w)).where("g = 1").select("scheme", "t", "loss")


# ------------------------------------------------------------------ Hessians and rates
def embedding_range(h: np.ndarray, approx: np.ndarray, rcond: float = 1e-10) -> tuple[float, float]:
    """Extreme eigenvalues of the approximation relative to the exact Hessian."""
    e, v = np.linalg.eigh(h)
    keep = e > rcond * e.max()
    half = v[:, keep] / np.sqrt(e[keep])
    values = np.linalg.eigvalsh(half.T @ approx @ half)
    return float(values[0]), float(values[-1])


def embedding_eps(h: np.ndarray, approx: np.ndarray) -> float:
    low, high = embedding_range(h, approx)
    return max(1 - low, high - 1)


def failure_rate(eps: list[float], bound: float) -> float:
    """Share of draws whose error exceeds the bound."""
    return float(np.mean([e > bound for e in eps]))


def constants(h: np.ndarray, g: np.ndarray, approx: np.ndarray | None = None, rcond: float = 1e-10) -> dict:
    """k and M (extreme eigenvalues), eta (the least non-zero one), and nu (the share of
    the gradient in the range of the approximation)."""
    e = np.linalg.eigvalsh(h)
    a = h if approx is None else approx
    ea, va = np.linalg.eigh(a)
    u = va[:, ea > rcond * ea.max()]
    live = e[e > rcond * e.max()]
    return {"k": float(max(e[0], 0.0)), "M": float(e[-1]), "eta": float(live[0]), "nu": float(((u.T @ g) ** 2).sum() / max(g @ g, 1e-300))}


def global_rate(alpha: float, beta: float, k: float, m: float, eps: float) -> float:
    """1 - rho: the guaranteed contraction of the loss gap, strongly convex."""
    return 1 - 2 * alpha * beta * k / (m * (1 + eps))


def least_step(beta: float, eps: float, k: float, m: float) -> float:
    return 2 * (1 - beta) * (1 - eps) * k / m


def local_bound(gap: float, lipschitz: float, gamma: float, eps: float, beta: float) -> float:
    """The linear-quadratic bound on the next distance to the optimum."""
    return 25 * lipschitz / (8 * gamma) * gap**2 + 5 * eps * beta / gamma * gap


def local_bound_applies(eps: float, gamma: float, beta: float) -> bool:
    return eps <= gamma / (8 * beta)


def weak_rate(alpha: float, beta: float, nu: float, eps: float, eta: float, m: float) -> float:
    """The guaranteed contraction of the squared gradient norm, weakly convex."""
    return 1 - 2 * beta * alpha * nu * (1 - eps) * eta / (m * (1 + eps))


def weak_step(beta: float, nu: float, eps: float, eta: float, m: float, lipschitz: float, g0: float) -> float:
    return eta / (2 * (lipschitz * g0 + m * m)) * ((1 - beta) * nu * eta - 2 * eps * m)


def perturbed(h: np.ndarray, eps: float, seed: int = 0) -> np.ndarray:
    """h changed so that its relative eigenvalues lie within 1 - eps and 1 + eps: a hook for
    tests of how much error of the Hessian a method bears."""
    e, v = np.linalg.eigh(h)
    half = v * np.sqrt(np.maximum(e, 0))
    a = np.random.default_rng(seed).normal(size=h.shape)
    a = a + a.T
    return half @ (np.eye(len(h)) + eps * a / np.linalg.norm(a, 2)) @ half.T
