"""A compressed FM-index over integer symbols: wavelet matrix, backward search, and
matching statistics of fixed length.

Every pattern step is vectorised over all patterns at once."""

from __future__ import annotations

import numpy as np

_U = np.uint64


class RankBits:
    """A packed bit vector with rank and select; half a bit more for each bit."""

    def __init__(self, bits: np.ndarray):
        packed = np.packbits(bits, bitorder="little")
        self.words = np.zeros(len(bits) // 64 + 1, np.uint64)
        self.words.view(np.uint8)[: len(packed)] = packed
        ones = np.bitwise_count(self.words).astype(np.int64)
        self.before = np.concatenate([[0], np.cumsum(ones)[:-1]]).astype(np.uint32)
        self.ones = int(ones.sum())

    def rank1(self, at: np.ndarray) -> np.ndarray:
        """Ones among the first ``at`` bits."""
        w = at >> 6
        low = (_U(1) << (at & 63).astype(np.uint64)) - _U(1)
        return self.before[w] + np.bitwise_count(self.words[w] & low).astype(np.int64)

    def select1(self, k: np.ndarray) -> np.ndarray:
        """Where the k-th one stands, counting from 0."""
        w = np.searchsorted(self.before, k, side="right") - 1
        word, rest, at = self.words[w], k - self.before[w].astype(np.int64), np.zeros(len(k), np.int64)
        for width in (32, 16, 8, 4, 2, 1):
            low = np.bitwise_count((word >> at.astype(np.uint64)) & ((_U(1) << _U(width)) - _U(1))).astype(np.int64)
            on = rest >= low
            rest -= np.where(on, low, 0)
            at += np.where(on, width, 0)
        return (w << 6) + at


class WaveletMatrix:
    def __init__(self, symbols: np.ndarray, levels: int):
        self.n, self.levels = len(symbols), []
        for shift in range(levels - 1, -1, -1):
            bit = ((symbols >> shift) & 1).astype(bool)
            self.levels.append((shift, RankBits(bit), int(len(bit) - bit.sum())))
            symbols = np.concatenate([symbols[~bit], symbols[bit]])

    def rank(self, c: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How often c occurs before lo and before hi (elementwise)."""
        start = np.zeros(len(c), np.int64)
        m = len(c)
        for shift, bits, zeros in self.levels:
            one = ((c >> shift) & 1).astype(bool)
            r = bits.rank1(np.concatenate([start, lo, hi]))
            rs, rl, rh = r[:m], r[m : 2 * m], r[2 * m :]
            start = np.where(one, zeros + rs, start - rs)
            lo = np.where(one, zeros + rl, lo - rl)
            hi = np.where(one, zeros + rh, hi - rh)
        return lo - start, hi - start


class FMIndex:
    """An index of pieces (short symbol sequences, symbols 1 .. sigma, depth 2 or more), with
    a value for each.

    Pieces end in unique separators that sort below all symbols.  What stays after building
    is packed: the wavelet matrix of the transformed text, two bit vectors that mark where
    the rows of the suffix array change in their first ``depth`` (or one less) symbols, and
    for each run of the former, that is for each distinct window, the least value of the
    pieces that hold it."""

    def __init__(self, symbols: np.ndarray, sizes: np.ndarray, sigma: int, depth: int, value: np.ndarray):
        k, total = len(sizes), int(sizes.sum())
        n = total + k
        self.depth, self.sigma, self.n = depth, sigma, n
        ends = np.cumsum(sizes + 1) - 1
        text = np.empty(n, np.int64)
        inside = np.ones(n, bool)
        inside[ends] = False
        text[inside] = symbols + k
        text[ends] = np.arange(k)
        suffix, half, part = self._sorted(text, depth)
        self.full = RankBits(self._edges(half, suffix, depth - part))
        # rows that share all but the last symbol of a window: where a step to the left starts
        self.short = RankBits(self._edges(half, suffix, depth - 1 - part))
        piece = np.repeat(np.arange(k), sizes + 1)
        self.least = np.minimum.reduceat(value[piece[suffix]], self.full.select1(np.arange(self.full.ones))) if n else value
        plain = np.where(inside, text - k, 0)
        self.below = np.concatenate([[0], np.cumsum(np.bincount(plain, minlength=sigma + 2))])
        self.matrix = WaveletMatrix(plain[suffix - 1], int(sigma + 1).bit_length())

    @staticmethod
    def _sorted(text: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray, int]:
        """The suffix array by doubling, and the ranks by the first ``part`` symbols, the
        greatest power of two below ``depth``."""
        n, width, half, part = len(text), 1, None, 1
        rank = np.unique(text, return_inverse=True)[1]
        while part * 2 < depth:
            part *= 2
        order = np.argsort(rank, kind="stable")
        while n:
            if width == part:
                half = rank
            nxt = np.zeros(n, np.int64)
            nxt[: n - width] = rank[width:] + 1
            key = rank * np.int64(n + 1) + nxt
            order = np.argsort(key, kind="stable")
            same = key[order[1:]] == key[order[:-1]]
            new = np.concatenate([[0], np.cumsum(~same)])
            rank = np.empty(n, np.int64)
            rank[order] = new
            width *= 2
            if half is not None and (not same.any() or width > 2 * n):
                break
        return order, half if n else rank, part

    @staticmethod
    def _edges(rank: np.ndarray, suffix: np.ndarray, rest: int) -> np.ndarray:
        """Rows whose first symbols differ from the row's before: ``rank`` of a place and
        of the one ``rest`` further tell them apart."""
        if not len(suffix):
            return np.zeros(0, bool)
        a, b = rank[suffix], rank[np.minimum(suffix + rest, len(rank) - 1)]
        return np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])

    def step(self, c: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """One backward step: the rows whose suffixes start with c and then match.  Symbols
        above sigma match nothing."""
        a, b = self.matrix.rank(c, lo, hi)
        return self.below[c] + a, self.below[c] + b

    def shortened(self, row: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows that share all but the last symbol of the window at ``row``."""
        run = self.short.rank1(row + 1) - 1
        last = run + 1 == self.short.ones
        return self.short.select1(run), np.where(last, self.n, self.short.select1(np.minimum(run + 1, self.short.ones - 1)))

    def matches(self, symbols: np.ndarray, sizes: np.ndarray):
        """Matching statistics of the patterns (symbols 1 .. sigma + 1), cut at ``depth``:
        yields, from the last window to the first, (pattern, window start, least value,
        found); where a window isn't in the index the value means nothing."""
        d, start = self.depth, np.concatenate([[0], np.cumsum(sizes)[:-1]])
        who = np.flatnonzero(sizes >= d)
        at = sizes[who] - 1
        lo, hi = np.zeros(len(who), np.int64), np.full(len(who), self.n)
        for _ in range(d):
            lo, hi = self.step(symbols[start[who] + at], lo, hi)
            at = at - 1
        at = at + 1
        while len(who):
            found = hi > lo
            row = np.minimum(lo, self.n - 1)
            yield who, at, self.least[self.full.rank1(row + 1) - 1], found
            go = at > 0
            who, at, row, found = who[go], at[go] - 1, row[go], found[go]
            left, right = self.shortened(row)
            lo, hi = self.step(symbols[start[who] + at], left, right)
            lost = np.flatnonzero(~found)
            if len(lost):  # nothing to shorten: these windows are searched from their end
                left, right = np.zeros(len(lost), np.int64), np.full(len(lost), self.n)
                for j in range(d - 1, -1, -1):
                    left, right = self.step(symbols[start[who[lost]] + at[lost] + j], left, right)
                lo[lost], hi[lost] = left, right
