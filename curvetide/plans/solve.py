"""Dense solves at the driver: Cholesky, pseudo-inverse, conjugate gradients, minimum
residual; and conjugate gradients on a distributed matrix."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def solve_spd(h: np.ndarray, g: np.ndarray) -> np.ndarray:
    c = np.linalg.cholesky(h)
    return np.linalg.solve(c.T, np.linalg.solve(c, g))


def pinv_solve(h: np.ndarray, g: np.ndarray, rcond: float = 1e-8) -> np.ndarray:
    """The minimum-norm minimiser of |h p - g|: eigenvalues below rcond of the top count
    as zero."""
    e, v = np.linalg.eigh((h + h.T) / 2)
    keep = e > rcond * max(e.max(), 1e-300)
    return v[:, keep] @ ((v[:, keep].T @ g) / e[keep])


def cg(mul: Callable[[np.ndarray], np.ndarray], g: np.ndarray, tol: float = 1e-8, most: int | None = None) -> np.ndarray:
    x, r = np.zeros_like(g), g.copy()
    p, rr = r.copy(), float(r @ r)
    stop = tol * np.sqrt(rr)
    for _ in range(most or 2 * len(g)):
        if np.sqrt(rr) <= stop:
            break
        q = mul(p)
        a = rr / float(p @ q)
        x, r = x + a * p, r - a * q
        new = float(r @ r)
        p, rr = r + new / rr * p, new
    return x


def minres(mul: Callable[[np.ndarray], np.ndarray], g: np.ndarray, tol: float = 1e-10, most: int | None = None) -> np.ndarray:
    """Minimum residual for symmetric, possibly singular matrices: Lanczos vectors and the
    small least-squares problem on their tridiagonal matrix."""
    beta0 = float(np.linalg.norm(g))
    if beta0 == 0:
        return np.zeros_like(g)
    q, alphas, betas = [g / beta0], [], []
    best = np.zeros_like(g)
    for k in range(most or len(g)):
        v = mul(q[k])
        alphas.append(float(q[k] @ v))
        v = v - alphas[k] * q[k] - (betas[-1] * q[k - 1] if k else 0)
        v -= np.stack(q, 1) @ (np.stack(q, 1).T @ v)
        b = float(np.linalg.norm(v))
        t = np.zeros((k + 2, k + 1))
        for i in range(k + 1):
            t[i, i] = alphas[i]
            if i:
                t[i - 1, i] = t[i, i - 1] = betas[i - 1]
        t[k + 1, k] = b
        e = np.zeros(k + 2)
        e[0] = beta0
        z, *_ = np.linalg.lstsq(t, e, rcond=1e-12)
        best = np.stack(q, 1) @ z
        if np.linalg.norm(t @ z - e) < tol * beta0 or b < 1e-12 * abs(alphas[0] or 1):
            break
        betas.append(b)
        q.append(v / b)
    return best


def cg_distributed(h: DataFrame, g: np.ndarray, tol: float = 1e-8, most: int = 50) -> np.ndarray:
    """Conjugate gradients on (i, j, h) entries with i <= j; one job for each step."""
    d, spark = len(g), h.sparkSession
    full = h.unionByName(h.where("i < j").select(F.col("j").alias("i"), F.col("i").alias("j"), "h")).cache()

    def mul(p: np.ndarray) -> np.ndarray:
        v = F.broadcast(spark.createDataFrame([(i, float(x)) for i, x in enumerate(p)], "j int, p double"))
        rows = full.join(v, "j").groupBy("i").agg(F.sum(F.col("h") * F.col("p")).alias("s")).collect()
        out = np.zeros(d)
        for r in rows:
            out[r["i"]] = r["s"]
        return out

    try:
        return cg(mul, g, tol, most)
    finally:
        full.unpersist()
