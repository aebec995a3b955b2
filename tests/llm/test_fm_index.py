import numpy as np

from curvetide.llm.fm_index import FMIndex, RankBits, WaveletMatrix


def test_rank_and_wavelet():
    rng = np.random.default_rng(0)
    bits = rng.random(1000) < 0.3
    r = RankBits(bits)
    at = np.arange(1001)
    assert (r.rank1(at) == np.concatenate([[0], np.cumsum(bits)])).all()
    ones = np.flatnonzero(bits)
    assert (r.select1(np.arange(len(ones))) == ones).all() and r.ones == len(ones)
    x = rng.integers(0, 37, 500)
    w = WaveletMatrix(x, 6)
    c = rng.integers(0, 37, 200)
    lo, hi = rng.integers(0, 250, 200), rng.integers(250, 501, 200)
    a, b = w.rank(c, lo, hi)
    assert [int((x[:i] == s).sum()) for s, i in zip(c, lo)] == a.tolist()
    assert [int((x[:i] == s).sum()) for s, i in zip(c, hi)] == b.tolist()


def test_matching_statistics():
    rng = np.random.default_rng(1)
    depth = 5
    pieces = [rng.integers(1, 4, rng.integers(depth, 14)) for _ in range(60)]
    size = np.array([len(p) for p in pieces])
    value = np.arange(100, 160)
    index = FMIndex(np.concatenate(pieces), size, 4, depth, value)
    asked = [rng.integers(1, 6, rng.integers(2, 14)) for _ in range(80)]
    found = {}
    for who, at, least, hit in index.matches(np.concatenate(asked), np.array([len(p) for p in asked])):
        for w, a, b, h in zip(who, at, least, hit):
            found[int(w), int(a)] = int(b) if h else None
    for w, p in enumerate(asked):
        for a in range(len(p) - depth + 1):
            inside = [v for v, q in zip(value, pieces) if any((q[i : i + depth] == p[a : a + depth]).all() for i in range(len(q) - depth + 1))]
            assert found[w, a] == (min(inside) if inside else None)


def test_size_of_an_index():
    rng = np.random.default_rng(2)
    size = np.full(2000, 20)
    index = FMIndex(rng.integers(1, 300, size.sum()), size, 299, 13, np.arange(2000))
    held = sum(b.words.nbytes + b.before.nbytes for b in [index.full, index.short, *(x for _, x, _ in index.matrix.levels)])
    assert held * 8 < 1.6 * (9 + 2) * index.n and index.least.nbytes <= 8 * index.n
    assert not any(isinstance(v, np.ndarray) and len(v) >= index.n for k, v in vars(index).items() if k != "least")


def test_empty_index():
    index = FMIndex(np.zeros(0, np.int64), np.zeros(0, np.int64), 0, 5, np.zeros(0, np.int64))
    assert index.n == 0
