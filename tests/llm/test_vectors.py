import numpy as np

from curvetide.llm import embedding_dedup as E

SCHEMA = "vec_id long, embedding array<float>, label int, n_links long"


def brute(rows, least=0.98):
    ids, out = [r[0] for r in rows], {}
    unit = []
    for _, v, k, *_ in rows:
        x = np.array([np.nan if t is None else t for t in (v or [])], np.float64)
        n = np.sqrt((x * x).sum()) if len(x) else 0
        unit.append(x / n if k is not None and np.isfinite(n) and n > 0 else None)
    comp = {i: i for i in ids}

    def root(i):
        while comp[i] != i:
            i = comp[i]
        return i

    links = dict.fromkeys(ids, 0)
    for a in range(len(rows)):
        for b in range(a):
            if unit[a] is not None and unit[b] is not None and rows[a][2] == rows[b][2] and len(unit[a]) == len(unit[b]) and unit[a] @ unit[b] >= least:
                links[ids[a]] += 1
                links[ids[b]] += 1
                p, q = sorted((root(ids[a]), root(ids[b])))
                comp[q] = p
    return {i: (links[i], root(i), root(i) == i) for i in ids}


def test_against_brute_force(spark):
    rng = np.random.default_rng(3)
    rows, i = [], 0
    for label in range(3):
        for n in (1, 2, 5, 60):
            base = rng.normal(size=16)
            for _ in range(n):
                rows.append((i, [float(t) for t in base + rng.normal(size=16) * 0.12], label, 1))
                i += 1
        for _ in range(60):
            rows.append((i, [float(t) for t in rng.normal(size=16)], label, 1))
            i += 1
    rows = [(a, np.array(v, np.float32).astype(float).tolist(), k, n) for a, v, k, n in rows]
    rows += [(i, rows[0][1], 0, 1), (i + 1, rows[0][1], 1, 1), (i + 2, rows[0][1], None, 1), (i + 3, [0.0] * 16, 0, 1), (i + 4, None, 0, 1), (i + 5, [float("nan")] * 16, 0, 1), (i + 6, [None] * 16, 0, 1), (i + 7, [], 0, 1), (i + 8, [1.0, 2.0], 0, 1), (i + 9, [1.0, 2.0], 0, 1), (i + 10, [2 * t for t in rows[0][1]], 0, 1)]
    rows += [(i + 11 + j, [float(t) for t in v], j % 2, 1) for j, v in enumerate(np.repeat(rng.normal(size=(20, 5)), 3, axis=0))]
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in E.near_vectors(spark.createDataFrame(rows, SCHEMA)).collect()}
    want = brute(rows)
    found = sum(v[0] for v in got.values())
    exact = sum(v[0] for v in want.values())
    assert all(got[k][0] <= want[k][0] for k in want) and found >= 0.97 * exact
    assert len(got) == len(rows) and sum(got[k] == want[k] for k in want) >= 0.97 * len(want)


def test_edges(spark):
    assert E.near_vectors(spark.createDataFrame([], SCHEMA)).count() == 0
    only = E.near_vectors(spark.createDataFrame([(1, None, 1, 0), (None, [1.0], None, 0)], SCHEMA)).collect()
    assert [(r["n_links"], r["kept"]) for r in only] == [(0, True)] * 2


def wide(rows):
    return [(a, v, k, 0) for a, v, k in rows]


def test_scales_and_lengths(spark):
    schema = SCHEMA.replace("float", "double")
    rows = wide([(1, [1e200, 1e200], 0), (2, [2e-170, 2e-170], 0), (3, [1.0, -1.0], 0), (4, [3.0, 3.0], 0), (5, [1.0], 0), (6, [2.0], 0), (7, [-2.0], 0), (8, [1.0] * 300, 0), (9, [5.0] * 300, 0), (10, [float("inf"), 1.0], 0)])
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in E.near_vectors(spark.createDataFrame(rows, schema)).collect()}
    assert got == {1: (2, 1), 2: (2, 1), 4: (2, 1), 3: (0, 3), 5: (1, 5), 6: (1, 5), 7: (0, 7), 8: (1, 8), 9: (1, 8), 10: (0, 10)}


def test_one_id_with_two_vectors(spark):
    rows = wide([(1, [1.0, 0.0], 0), (1, [0.0, 1.0], 0), (2, [2.0, 0.0], 0), (3, [0.0, 3.0], 0), (1, [0.0, 1.0], 0), (4, [1.0, -1.0], 0)])
    got = sorted((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in E.near_vectors(spark.createDataFrame(rows, SCHEMA)).collect())
    assert got == [(1, 1, 1, True), (1, 2, 1, True), (1, 2, 1, True), (2, 1, 1, False), (3, 2, 1, False), (4, 0, 4, True)]


def test_large_group_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(E, "BLOCK", 60)
    rng = np.random.default_rng(9)
    base = rng.normal(size=24)
    rows = wide([(i, [float(t) for t in base + rng.normal(size=24) * 0.09], 0) for i in range(300)] + [(500 + i, [float(t) for t in rng.normal(size=24)], 0) for i in range(300)])
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in E.near_vectors(spark.createDataFrame(rows, SCHEMA.replace("float", "double"))).collect()}
    want = brute(rows)
    found, exact = sum(v[0] for v in got.values()), sum(v[0] for v in want.values())
    assert exact > 10_000 and all(got[k][0] <= want[k][0] for k in want) and found >= 0.99 * exact
    assert sum(got[k][1:] == want[k][1:] for k in want) >= 0.99 * len(want)


def test_chunks_grow_with_the_table():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(2000, 48))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    few, many = (E.plan_tables({48: x}, n, 0.98) for n in (1000, 1_000_000))
    assert many.width > few.width and many.count > few.count
    a, b = E.simulated_pairs(x, 0.98, seed=77)
    assert np.allclose((a * b).sum(axis=1), 0.98)
    for t in (few, many):
        p, q = t.codes(a), t.codes(b)
        assert (p == q).any(axis=1).mean() > 0.985 and (np.bitwise_count(p ^ q).sum(axis=1) <= t.radius).mean() > 0.99
        far = t.codes(x)
        assert (far[:-1] == far[1:]).any(axis=1).mean() < 5 * t.count / 2 ** (t.width - 1) + 0.02


def test_rotation_balances_and_keeps_neighbours():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(2000, 32)) * np.linspace(3, 0.3, 32)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    q = E.learn(x)
    bits = q.bits(x)
    assert (np.abs(bits.mean(axis=0) - 0.5) < 0.2).all()
    assert np.allclose(q.turn.T @ q.turn, np.eye(32), atol=1e-8)
    loss = lambda t: np.square(np.where((x - q.mean) @ t >= 0, 1, -1) - (x - q.mean) @ t).sum()
    other = np.linalg.qr(rng.normal(size=(32, 32)))[0]
    assert loss(q.turn) < loss(other)
