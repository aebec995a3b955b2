"""A small semidefinite program by a log-determinant barrier: minimise c.x where
F_0 + sum x_i F_i is positive definite.  Matrices are small and live at the driver; the
root of the Hessian has a row for each entry of a p x p matrix and may be sketched."""

from __future__ import annotations

import numpy as np

from ..operators.sketch import BlockSketch
from .solve import solve_spd


def _state(f0, fs, x):
    return f0 + np.tensordot(x, fs, axes=1)


def root(f0, fs, x) -> np.ndarray:
    """(p * p, n): the matrices S^-1/2 F_i S^-1/2 as columns."""
    e, v = np.linalg.eigh(_state(f0, fs, x))
    half = (v / np.sqrt(e)) @ v.T
    return np.stack([(half @ f @ half).reshape(-1) for f in fs], axis=1)


def solve(f0, fs, cost, x0, tau: float = 1.0, growth: float = 10.0, stages: int = 6, inner: int = 12, sketch: BlockSketch | None = None) -> np.ndarray:
    f0, fs, c, x = np.asarray(f0, float), np.asarray(fs, float), np.asarray(cost, float), np.asarray(x0, float)
    if np.linalg.eigvalsh(_state(f0, fs, x))[0] <= 0:
        raise ValueError("the start isn't strictly feasible")

    def value(v, t):
        e = np.linalg.eigvalsh(_state(f0, fs, v))
        return np.inf if e[0] <= 0 else t * float(c @ v) - float(np.log(e).sum())

    for k in range(stages):
        for it in range(inner):
            inv = np.linalg.inv(_state(f0, fs, x))
            g = tau * c - np.tensordot(fs, inv, axes=([1, 2], [0, 1]))
            a = root(f0, fs, x)
            if sketch is not None:
                now = sketch.fresh(100 * k + it)
                into = {b: np.zeros((now.width, len(x))) for b in range(now.blocks)}
                now.scatter(np.arange(len(a)), a, into, range(now.blocks))
                a = np.concatenate(list(into.values())) / np.sqrt(now.blocks)
            p = -solve_spd(a.T @ a + 1e-12 * np.eye(len(x)), g)
            step, here = 1.0, value(x, tau)
            while step > 1e-9 and value(x + step * p, tau) > here + 0.1 * step * float(p @ g):
                step /= 4
            x = x + step * p
            if abs(float(p @ g)) < 1e-9:
                break
        tau *= growth
    return x
