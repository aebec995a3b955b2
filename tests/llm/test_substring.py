import random

from curvetide.llm import common as C
from curvetide.llm import substring_dedup as S


def brute(pairs, window=13):
    words = [(i, [] if t is None else t.encode().split()) for i, t in pairs]
    first = {}
    for i, w in words:
        if i is not None:
            for k in range(len(w) - window + 1):
                g = tuple(w[k : k + window])
                first[g] = min(i, first.get(g, i))
    out = []
    for i, w in words:
        gone = [False] * len(w)
        if i is not None:
            for k in range(len(w) - window + 1):
                if first[tuple(w[k : k + window])] < i:
                    gone[k : k + window] = [True] * window
        out.append((i, len(w), sum(gone), " ".join(x.decode() for x, g in zip(w, gone) if not g)))
    return sorted(out, key=str)


def test_against_brute_force(docs):
    rng = random.Random(4)
    vocab = [f"w{i}" for i in range(40)] + ["é", "中", "x" * 90]
    passages = [[rng.choice(vocab) for _ in range(rng.randint(13, 40))] for _ in range(6)]
    pairs = []
    for i in range(60):
        text = [rng.choice(vocab) for _ in range(rng.randint(0, 60))]
        for _ in range(rng.randint(0, 2)):
            k = rng.randint(0, len(text))
            text[k:k] = rng.choice(passages)
        pairs.append((i, " \t\n".join(text) if i % 7 else "\n ".join(text)))
    pairs += [(100, "the " * 5000), (101, "the " * 40), (102, None), (103, ""), (104, " \n"), (None, "the " * 40), (105, "a b\x1cc " * 20), (5, pairs[5][1])]
    got = S.remove_repeats(docs(pairs)).select("doc_id", "n_words", "n_removed", "kept").collect()
    assert sorted(map(tuple, got), key=str) == brute(pairs)


def test_windows_of_all_sizes(docs):
    import pytest

    rng = random.Random(5)
    vocab = [f"w{i}" for i in range(30)]
    passages = [[rng.choice(vocab) for _ in range(n)] for n in (8, 60, 150, 260, 420)]
    pairs = []
    for i in range(40):
        text = [rng.choice(vocab) for _ in range(rng.randint(0, 50))]
        for p in rng.sample(passages, 2):
            text[rng.randint(0, len(text)) :] += p
        pairs.append((i, " ".join(text)))
    for window in (6, 7, 64, 131, 150, 200):
        got = S.remove_repeats(docs(pairs), window).select("doc_id", "n_words", "n_removed", "kept").collect()
        assert sorted(map(tuple, got), key=str) == brute(pairs, window), window
    for window in (5, 201):
        with pytest.raises(ValueError):
            S.remove_repeats(docs(pairs), window)


def test_patterns_that_no_index_holds():
    """Later stretches share an anchor with earlier ones but not all of their windows."""
    import numpy as np

    rng = np.random.default_rng(3)
    common = min((rng.integers(1, 1 << 40, S.RUN).astype(np.uint64) for _ in range(300)), key=lambda w: C.window_hashes(w, S.RUN)[0])
    low = C.window_hashes(common, S.RUN)[0]
    sides, size, docs = [], [], []
    while len(sides) < 12:  # stretches around a common run that is their anchor
        head, tail = rng.integers(1, 1 << 40, 7).astype(np.uint64), rng.integers(1, 1 << 40, 7).astype(np.uint64)
        if len(sides) % 3:
            tail = sides[-1][-7:]
        words = np.concatenate([head, common, tail])
        if C.window_hashes(words, S.RUN).min() == low:
            sides.append(words)
            size.append(len(words))
            docs.append(int(rng.integers(0, 6)))
    docs, size = np.array(docs), np.array(size)
    result, asked = S.earliest(np.concatenate(sides), size, docs, docs, 13)
    assert asked.tolist() == (docs > docs.min()).tolist() and 0 < asked.sum() < 12
    at, lost = 0, 0
    for words, n, d, q in zip(sides, size, docs, asked):
        for k in range(n - 12):
            if q:
                have = [e for other, e in zip(sides, docs) for j in range(len(other) - 12) if (other[j : j + 13] == words[k : k + 13]).all() and e < docs.max()]
                assert result[at + k] == min(have, default=S._NOBODY)
                lost += not have
        at += n - 12
    assert lost


def test_spans(docs):
    text = " ".join(f"w{i}" for i in range(20))
    rows = S.remove_repeats(docs([(1, text), (2, "a b " + text + " c " + text)])).collect()
    got = {r["doc_id"]: [(x["lo"], x["hi"]) for x in r["spans"]] for r in rows}
    assert got == {1: [], 2: [(2, 22), (23, 43)]}


def test_empty_table(docs, spark):
    assert S.remove_repeats(docs([])).count() == 0
    assert S.without_repeats(docs([])).columns == ["doc_id", "text", "lang", "source", "n_chars"]


def test_other_columns_stay(docs):
    from pyspark.sql import functions as F

    text = " ".join(f"w{i}" for i in range(30))
    df = docs([(1, text), (2, "start " + text), (3, text), (4, "a\n\nb")]).withColumn("kept", F.lit("mine")).withColumn("n_words", F.lit(None).cast("int"))
    df = df.withColumns({"at": F.expr("timestamp'2024-02-03 04:05:06.123456'"), "day": F.expr("date'1999-12-31'"), "raw": F.lit(b"\x00\xff").cast("binary"), "cash": F.expr("cast(1.25 as decimal(20,7))"), "deep": F.expr("map('k', array(struct(doc_id as a, cast('NaN' as double) as b)))"), "local": F.expr("timestamp_ntz'2024-02-03 04:05:06.123456'")})
    rows = {r["doc_id"]: r for r in S.without_repeats(df).collect()}
    assert sorted(rows) == [1, 2, 4]  # 3 lost every word
    assert rows[2]["text"] == "start" and rows[2]["n_chars"] == 5 and rows[2]["kept"] == "mine" and rows[2]["n_words"] is None
    before = {r["doc_id"]: r for r in df.collect()}
    assert [f.dataType.simpleString() for f in S.without_repeats(df).schema] == [f.dataType.simpleString() for f in df.schema] and str(rows[2]["at"]).endswith(".123456")
    for i in rows:
        assert all(str(rows[i][c]) == str(before[i][c]) for c in ("at", "day", "raw", "cash", "deep", "local", "lang"))
    assert rows[4]["text"] == "a\n\nb" and rows[1]["text"] == text


def test_narrow_numbers():
    import numpy as np

    a = np.array([0, 1, 2**40 - 1, 123456789], np.uint64)
    assert (S.widen(S.narrow(a, 5), 5) == a).all()
    b = np.array([-5, 0, 7, 2**62], np.int64)
    assert (S._unsqueezed(S._squeezed(b)) == b).all()
