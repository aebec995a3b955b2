"""Hashed sparse linear models: feature counts of whole texts and their training."""

from __future__ import annotations

import numpy as np

from . import common as C

_U = np.uint64


# ------------------------------------------------------------------ byte n-grams
def byte_counts(text: bytes, dim: int, orders=(1, 2, 3, 4)) -> np.ndarray:
    """Counts of the hashed byte n-grams of a text; letters lose their case, and all
    other ASCII bytes count as one blank."""
    b = _FOLD[np.frombuffer(b" " + text + b" ", np.uint8)].astype(np.uint32)
    out = np.zeros(dim, np.int64)
    mask = np.uint32(dim - 1)
    code = np.zeros(len(b), np.uint32)
    for n in range(1, max(orders) + 1):
        code = code[: len(b) - n + 1] * np.uint32(0x01000193) + b[n - 1 :] if n > 1 else b.copy()
        if n in orders and len(code):
            x = (code + np.uint32(n)) * np.uint32(0x9E3779B1)
            out += np.bincount(((x >> np.uint32(13)) ^ x) & mask, minlength=dim)
    return out


_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[:128] = 32
_FOLD[97:123] = np.arange(97, 123)
_FOLD[65:91] = np.arange(97, 123)


def damped(counts: np.ndarray) -> np.ndarray:
    """Square roots of relative frequencies: rows of unit length."""
    x = np.sqrt(counts, dtype=np.float64)
    return x / np.maximum(np.sqrt((x * x).sum(axis=-1, keepdims=True)), 1e-12)


# ------------------------------------------------------------------ word n-grams
_KIND = np.zeros(256, np.uint8)  # 0 blank, 1 letter or digit or non-ASCII, 2 other
_KIND[33:128] = 2
_KIND[48:58] = 1
_KIND[65:91] = 1
_KIND[97:123] = 1
_KIND[128:] = 1


def word_ngrams(texts: list[bytes], dim: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashed 1- and 2-grams of tokens (runs of letters, runs of other characters) of each
    text: (feature ids, offsets of the texts).  Token hashes carry no case; a token of
    capitals and a token that repeats its predecessor add features of their own."""
    w = _Tokens(texts)
    h = w.hashes()
    two = C.mix64(h[1:] * _U(3) + h[:-1]) if len(h) else h
    again = np.zeros(len(h), bool)
    if len(h):
        again[1:] = h[1:] == h[:-1]
    doc = np.repeat(np.arange(len(texts)), np.diff(w.ptr))
    first = np.zeros(len(h), bool)
    first[w.ptr[:-1][np.diff(w.ptr) > 0]] = True
    pair_ok = ~first[1:]
    again &= ~first
    caps = w.capitals()
    mask = _U(dim - 1)
    ids = np.concatenate([h & mask, two[pair_ok] & mask, np.full(again.sum(), 1, np.uint64), np.full(caps.sum(), 2, np.uint64)]).astype(np.int64)
    of = np.concatenate([doc, doc[1:][pair_ok], doc[again], doc[caps]])
    order = np.argsort(of, kind="stable")
    return ids[order], np.searchsorted(of[order], np.arange(len(texts) + 1))


class _Tokens(C.Words):
    def __init__(self, texts: list[bytes]):
        raw = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
        kind = _KIND[raw]
        edge = np.concatenate([[True], kind[1:] != kind[:-1]])
        at = np.flatnonzero(edge)
        end = np.concatenate([at[1:], [len(raw)]])
        live = kind[at] > 0
        self.raw, self.buf = raw, C._LOWER[raw]
        self.start, self.end = at[live], end[live]
        bounds = np.cumsum([0] + [len(t) + 1 for t in texts])
        self.ptr = np.searchsorted(self.start, bounds)

    def capitals(self) -> np.ndarray:
        upper = np.concatenate([[0], np.cumsum((self.raw >= 65) & (self.raw <= 90))])
        size = self.end - self.start
        return (upper[self.end] - upper[self.start] == size) & (size > 1)


def sparse_rows(ids: np.ndarray, ptr: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """(feature, value) of each text; values are damped counts of unit length."""
    out = []
    for a, b in zip(ptr[:-1], ptr[1:]):
        f, n = np.unique(ids[a:b], return_counts=True)
        v = np.sqrt(n)
        out.append((f, v / max(np.sqrt((v * v).sum()), 1e-12)))
    return out


def sigmoid(t):
    return 1.0 / (1.0 + np.exp(-np.clip(t, -60, 60)))


class FTRL:
    """Logistic regression by follow-the-regularised-leader proximal updates: the weights
    are a closed form of accumulated gradients, sparse by the L1 term."""

    def __init__(self, dim: int, alpha=0.8, beta=1.0, l1=0.002, l2=0.01):
        self.z, self.n, self.bias = np.zeros(dim), np.zeros(dim), [0.0, 0.0]
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2

    def weights(self, f=slice(None)) -> np.ndarray:
        z, n = self.z[f], self.n[f]
        w = -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= self.l1, 0.0, w)

    def intercept(self) -> float:
        z, n = self.bias
        return -z / ((self.beta + n**0.5) / self.alpha + self.l2)

    def update(self, f: np.ndarray, x: np.ndarray, y: int, weight: float = 1.0) -> None:
        w, c = self.weights(f), self.intercept()
        e = weight * float(sigmoid(w @ x + c) - y)
        g = e * x
        n = self.n[f]
        self.z[f] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[f] = n + g * g
        z, m = self.bias
        self.bias = [z + e - ((m + e * e) ** 0.5 - m**0.5) / self.alpha * c, m + e * e]
