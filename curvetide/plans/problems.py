"""Objectives.  Each gives per-row sums over a block of rows (NumPy, for Arrow batches):
losses at several points, the gradient, and the rows of a Hessian root; and a regulariser
that the driver adds once."""

from __future__ import annotations

import numpy as np


def _sig(t):
    e = np.exp(-np.abs(t))
    return np.where(t >= 0, 1 / (1 + e), e / (1 + e))


def _softplus(t):
    return np.log1p(np.exp(-np.abs(t))) + np.maximum(t, 0)


class Problem:
    """``mean``: sums are divided by the number of rows.  ``convexity``: 'strong' or 'weak'."""

    convexity = "strong"
    mean = True
    lam = 0.0

    def width(self, d: int) -> int:
        """Length of the flat parameter vector."""
        return d

    def losses(self, x: np.ndarray, y: np.ndarray, ws: list[np.ndarray]) -> np.ndarray:
        raise NotImplementedError

    def gradient(self, x, y, w) -> np.ndarray:
        raise NotImplementedError

    def root(self, x, y, w) -> np.ndarray:
        """Rows whose Gram matrix is the Hessian's sum over these rows."""
        raise NotImplementedError

    def at_margins(self, t, y) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Losses, slopes and curvatures of the rows as functions of their products t."""
        raise NotImplementedError(f"{type(self).__name__} isn't a function of one product for each row")

    def reg_loss(self, w) -> float:
        return 0.5 * self.lam * float(w @ w)

    def reg_gradient(self, w) -> np.ndarray:
        return self.lam * w

    def reg_hessian(self, w) -> np.ndarray:
        return self.lam * np.eye(len(w))

    def errors(self, x, y, w) -> float:
        return float("nan")


class Logistic(Problem):
    """Mean of log(1 + exp(-y x.w)) plus lam / 2 |w|^2, for y = +-1."""

    def __init__(self, lam: float = 1e-4):
        self.lam = lam
        self.convexity = "strong" if lam > 0 else "weak"

    def losses(self, x, y, ws):
        return np.array([_softplus(-y * (x @ w)).sum() for w in ws])

    def gradient(self, x, y, w):
        return x.T @ (-y * _sig(-y * (x @ w)))

    def root(self, x, y, w):
        s = _sig(x @ w)
        return np.sqrt(s * (1 - s))[:, None] * x

    def at_margins(self, t, y):
        s = _sig(t)
        return _softplus(-y * t), -y * _sig(-y * t), s * (1 - s)

    def errors(self, x, y, w):
        return float((np.where(x @ w > 0, 1.0, -1.0) != y).sum())


class Softmax(Problem):
    """Sum of the negative log-likelihoods of K classes; parameters class by class.  Shifts
    of all classes by one vector change nothing, so it is weakly convex without lam."""

    mean = False

    def __init__(self, classes: int, lam: float = 0.0):
        self.k, self.lam = classes, lam
        self.convexity = "strong" if lam > 0 else "weak"

    def width(self, d):
        return d * self.k

    def _p(self, x, w):
        a = x @ w.reshape(self.k, -1).T
        top = a.max(axis=1, keepdims=True)
        e = np.exp(a - top)
        return a, top[:, 0], e, e.sum(axis=1)

    def losses(self, x, y, ws):
        out = []
        for w in ws:
            a, top, _, s = self._p(x, w)
            out.append((np.log(s) + top - a[np.arange(len(y)), y.astype(int)]).sum())
        return np.array(out)

    def gradient(self, x, y, w):
        _, _, e, s = self._p(x, w)
        b = e / s[:, None]
        b[np.arange(len(y)), y.astype(int)] -= 1
        return (b.T @ x).reshape(-1)

    def root(self, x, y, w):
        _, _, e, s = self._p(x, w)
        p = e / s[:, None]
        r = np.sqrt(p)[:, :, None] * (np.eye(self.k)[None] - p[:, None, :])
        return (r[:, :, :, None] * x[:, None, None, :]).reshape(len(x) * self.k, -1)

    def errors(self, x, y, w):
        return float(((x @ w.reshape(self.k, -1).T).argmax(axis=1) != y.astype(int)).sum())


class Ridge(Problem):
    """Half the mean squared residual plus lam / 2 |w|^2; plain least squares for lam 0."""

    def __init__(self, lam: float = 1e-3):
        self.lam = lam

    def losses(self, x, y, ws):
        return np.array([0.5 * ((x @ w - y) ** 2).sum() for w in ws])

    def gradient(self, x, y, w):
        return x.T @ (x @ w - y)

    def root(self, x, y, w):
        return x

    def at_margins(self, t, y):
        return 0.5 * (t - y) ** 2, t - y, np.ones_like(t)


class SquaredHinge(Problem):
    """Support vectors: half the mean squared hinge plus lam / 2 |w|^2."""

    def __init__(self, lam: float = 1e-3):
        self.lam = lam

    def losses(self, x, y, ws):
        return np.array([0.5 * (np.maximum(0, 1 - y * (x @ w)) ** 2).sum() for w in ws])

    def gradient(self, x, y, w):
        return x.T @ (-y * np.maximum(0, 1 - y * (x @ w)))

    def root(self, x, y, w):
        return x * (y * (x @ w) < 1)[:, None]

    def at_margins(self, t, y):
        short = np.maximum(0, 1 - y * t)
        return 0.5 * short**2, -y * short, (short > 0).astype(float)

    def errors(self, x, y, w):
        return float((np.where(x @ w > 0, 1.0, -1.0) != y).sum())


class LinearProgram(Problem):
    """tau c.x - sum log(b_i - a_i.x): the barrier of a program with rows a x <= b."""

    mean = False

    def __init__(self, cost, tau: float):
        self.c, self.tau = np.asarray(cost, float), tau

    def losses(self, x, y, ws):
        out = []
        for w in ws:
            slack = y - x @ w
            out.append(np.inf if (slack <= 0).any() else -np.log(slack).sum())
        return np.array(out)

    def gradient(self, x, y, w):
        return x.T @ (1 / (y - x @ w))

    def root(self, x, y, w):
        return x / np.abs(y - x @ w)[:, None]

    def reg_loss(self, w):
        return self.tau * float(self.c @ w)

    def reg_gradient(self, w):
        return self.tau * self.c

    def reg_hessian(self, w):
        return np.zeros((len(w), len(w)))


class LassoDual(Problem):
    """tau / 2 |y - z|^2 - sum log(lam - x_j.z) - sum log(lam + x_j.z) over the columns x_j
    of a dictionary: the barrier of projecting y on |X'z| <= lam."""

    mean = False

    def __init__(self, target, bound: float, tau: float):
        self.t, self.bound, self.tau = np.asarray(target, float), bound, tau

    def losses(self, x, y, ws):
        out = []
        for w in ws:
            a = x @ w
            bad = (np.abs(a) >= self.bound).any()
            out.append(np.inf if bad else -(np.log(self.bound - a) + np.log(self.bound + a)).sum())
        return np.array(out)

    def gradient(self, x, y, w):
        a = x @ w
        return x.T @ (1 / (self.bound - a) - 1 / (self.bound + a))

    def root(self, x, y, w):
        a = x @ w
        return np.sqrt(1 / (self.bound - a) ** 2 + 1 / (self.bound + a) ** 2)[:, None] * x

    def reg_loss(self, w):
        return 0.5 * self.tau * float((self.t - w) @ (self.t - w))

    def reg_gradient(self, w):
        return self.tau * (w - self.t)

    def reg_hessian(self, w):
        return self.tau * np.eye(len(w))

    def primal(self, alpha: np.ndarray) -> np.ndarray:
        """The lasso weights that belong to the products x_j.z at the barrier's optimum."""
        return (1 / (self.bound - alpha) - 1 / (self.bound + alpha)) / self.tau
