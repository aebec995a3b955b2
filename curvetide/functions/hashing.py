"""Retry-stable randomness: polynomial hashes of row ids, equal in SQL, NumPy and DuckDB.

A hash has two limbs, cubic polynomials over the prime field of 2**31 - 1 in the low and
the high part of a 62-bit id, added modulo the prime.  Each (seed, block) has coefficients
of its own, so the blocks of a sketch are independent and the values of a block are 4-wise
independent within a limb.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2147483647
_MASK = (1 << 64) - 1


def _splitmix(x: int) -> int:
    x = (x + 0x9E3779B97F4A7C15) & _MASK
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & _MASK
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & _MASK
    return x ^ (x >> 31)


def coefficients(seed: int, block: int = 0) -> tuple[int, ...]:
    """Seven field elements: four for the low limb, three for the high one."""
    base = _splitmix((seed << 20) ^ block)
    return tuple(_splitmix(base + k) % (P - 1) + 1 for k in range(7))


def hash_np(ids: np.ndarray, coef: tuple[int, ...]) -> np.ndarray:
    lo, hi = ids % P, ids // P
    h = np.full(len(ids), coef[0], np.int64)
    for c in coef[1:4]:
        h = (h * lo + c) % P
    g = np.full(len(ids), coef[4], np.int64)
    for c in coef[5:7]:
        g = (g * hi + c) % P
    return (h + g * hi) % P if hi.any() else h


def _fold(x: np.ndarray) -> np.ndarray:
    """A number below 2**64 that is equal modulo P and small: 2**31 == 1."""
    return (x & P) + (x >> 31)


def powers(ids: np.ndarray) -> list[np.ndarray]:
    """The cube, square and first power of the low limb, and of the high one unless it is 0
    throughout: what all hashes of these ids share."""
    out = []
    for v in (ids % P, ids // P % P):
        if not out or v.any():
            v = v.astype(np.uint64)
            square = _fold(_fold(v * v))
            out += [_fold(_fold(square * v)), square, v]
    return out


def hash_of(powers: list[np.ndarray], coef: tuple[int, ...]) -> np.ndarray:
    """``hash_np`` of the ids that have these powers."""
    h = _fold(powers[0] * coef[0] + powers[1] * coef[1] + powers[2] * coef[2] + coef[3])
    if len(powers) > 3:
        h += _fold(powers[3] * coef[4] + powers[4] * coef[5] + powers[5] * coef[6])
    h = _fold(h)
    return np.minimum(h, h - P).view(np.int64)  # below P h - P wraps around


def hash_col(row_id: Column, coef) -> Column:
    """coef: numbers, or columns of them."""
    lo = row_id % F.lit(P)
    hi = F.shiftright(row_id, 31) + F.shiftright((row_id.bitwiseAND(F.lit(P))) + F.shiftright(row_id, 31) + 1, 31)
    get = lambda k: coef[k] if isinstance(coef[k], Column) else F.lit(int(coef[k]))
    h = get(0)
    for k in (1, 2, 3):
        h = (h * lo + get(k)) % F.lit(P)
    g = get(4)
    for k in (5, 6):
        g = (g * hi + get(k)) % F.lit(P)
    return (h + (g * hi) % F.lit(P)) % F.lit(P)


def hash_sql(row_id: str, coef: tuple[int, ...]) -> str:
    """The low limb as SQL text (ids below the prime), for oracles."""
    h = str(coef[0])
    for c in coef[1:4]:
        h = f"(({h}) * ({row_id} % {P}) + {c}) % {P}"
    return f"({h})"


def hash_sql_long(row_id: str, coef: tuple[int, ...]) -> str:
    """Both limbs as SQL text, for ids beyond the prime."""
    g = str(coef[4])
    for c in coef[5:7]:
        g = f"(({g}) * ({row_id} // {P}) + {c}) % {P}"
    return f"(({hash_sql(row_id, coef)} + ({g}) * ({row_id} // {P}) % {P}) % {P})"


def uniform_col(row_id: Column, seed: int, block: int = 0) -> Column:
    """Uniform in [0, 1)."""
    return hash_col(row_id, coefficients(seed, block)) / F.lit(float(P))


def uniform_np(ids: np.ndarray, seed: int, block: int = 0) -> np.ndarray:
    return hash_np(ids, coefficients(seed, block)) / float(P)


def uniform_sql(row_id: str, seed: int, block: int = 0) -> str:
    return f"({hash_sql(row_id, coefficients(seed, block))} / {float(P)})"
