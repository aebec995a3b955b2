import random
import re

import numpy as np

from curvetide.llm import common as C
from curvetide.llm import near_dedup as N


def brute(pairs, k=4, percent=80):
    sets = []
    for _, t in pairs:
        w = re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode().lower() if t and t.isascii() else re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set()))
    ids = [i for i, _ in pairs]
    comp = dict((i, i) for i in ids)

    def root(i):
        while comp[i] != i:
            i = comp[i]
        return i

    for a in range(len(pairs)):
        for b in range(a):
            x, y = sets[a], sets[b]
            if x and y and None not in (ids[a], ids[b]) and 100 * len(x & y) >= percent * len(x | y):
                p, q = sorted((root(ids[a]), root(ids[b])))
                comp[q] = p
    return {i: (len(s), root(i), root(i) == i) for i, s in zip(ids, sets)}


def family(rng, vocab, n, size):
    base = [rng.choice(vocab) for _ in range(size)]
    out = []
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        out.append(" ".join(w))
    return out


def test_against_brute_force(docs):
    rng = random.Random(7)
    vocab = [f"t{i}" for i in range(3000)]
    texts = [t for n, size in ((40, 60), (20, 120), (15, 30), (60, 90)) for t in family(rng, vocab, n, size)]
    texts += [" ".join(rng.choice(vocab) for _ in range(80)) for _ in range(60)] + ["", None, "a b", "A  B", "a c", " \n", "x " * 3000, "É é é é", "é é é é"]
    rng.shuffle(texts)
    pairs = list(enumerate(texts)) + [(2000, texts[3]), (2001, texts[3])]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in N.near_duplicates(docs(pairs), 4, 80).collect()}
    assert got == brute(pairs)


def test_edge_cases(docs):
    assert N.near_duplicates(docs([])).count() == 0
    rows = N.near_duplicates(docs([(None, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (3, None)]), 4, 80).collect()
    assert sorted(((r["doc_id"], r["component_id"], r["kept"]) for r in rows), key=str) == [(1, 1, True), (1, 1, True), (3, 3, True), (None, None, True)]


def test_one_id_with_two_texts(docs):
    a, b = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    rows = N.near_duplicates(docs([(1, a), (1, b), (2, a + " more"), (3, b + " more"), (4, "c d e f g")]), 4, 80).collect()
    assert sorted((r["doc_id"], r["component_id"], r["kept"]) for r in rows) == [(1, 1, True), (1, 1, True), (2, 1, False), (3, 1, False), (4, 4, True)]


def test_a_leader_with_many_members(docs, monkeypatch):
    monkeypatch.setattr(N, "LEADER_SHINGLES", 300)
    rng = random.Random(3)
    vocab = [f"t{i}" for i in range(500)]
    pairs = list(enumerate(family(rng, vocab, 60, 80) + family(rng, vocab, 5, 30)))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in N.near_duplicates(docs(pairs), 4, 80).collect()}
    assert got == brute(pairs)


def test_filter_keeps_columns(docs):
    df = docs([(2, "one two three four five six"), (1, "One two three four five six"), (3, ""), (None, "one two three four five six")])
    out = N.without_near_duplicates(df, 5, 80)
    assert out.columns == df.columns and sorted((r["doc_id"] for r in out.collect()), key=str) == [1, 3, None]


def test_keys_cover_one_error_in_a_chunk():
    rng = np.random.default_rng(0)
    a = rng.integers(0, 1 << 16, (1, 32)).astype(np.uint16)
    for _ in range(100):
        b = a.copy()
        at = rng.choice(32, 15, replace=False)  # fewer than 2 * CHUNKS errors
        b[0, at] ^= 1
        assert set(N.signature_keys(a)[0]) & set(N.signature_keys(b)[0])


def test_components(spark):
    edges = [(i, i + 1) for i in range(200)] + [(500, 501), (501, 502), (502, 500), (900, 900)]
    got = {r["node"]: r["component"] for r in C.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(201)}, 500: 500, 501: 500, 502: 500}
    assert C.components(spark.createDataFrame([], "a long, b long")).count() == 0
