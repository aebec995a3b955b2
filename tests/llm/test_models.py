import random

import numpy as np

from curvetide.llm import language_id as L
from curvetide.llm import linear
from curvetide.llm import quality as Q
from curvetide.llm import common as C


def text(rng, syllables, n):
    return " ".join("".join(rng.choice(syllables) for _ in range(rng.randint(1, 3))) for _ in range(n))


TONGUES = {"en": ["the", "ing", "ed", "th"], "de": ["ung", "sch", "ß", "ein"], "fr": ["eau", "ç", "oi", "que"], "es": ["ción", "ñ", "ado", "ll"]}


def test_languages(spark):
    rng = random.Random(1)
    rows = [(i, text(rng, TONGUES[k], rng.randint(5, 200)), k) for i, k in enumerate(list(TONGUES) * 60)]
    rows += [(500, None, "en"), (501, "", "de"), (502, "12 + 3", "fr"), (503, text(rng, TONGUES["de"], 30), None), (None, text(rng, TONGUES["fr"], 30), "xx"), (7, rows[7][1], rows[7][2])]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = L.identify(df.withColumnRenamed("lang", "score_"), L.learn(df)).collect()
    by = {r["doc_id"]: r for r in got}
    assert sum(by[i]["lang_pred"] == k for i, _, k in rows[:240]) >= 239
    assert [by[i]["lang_pred"] for i in (500, 501, 502, 503, None)] == ["und", "und", "und", "de", "fr"]
    assert all(0 <= r["score"] <= 1 for r in got) and len(got) == len(rows)


def test_languages_by_brute_force(spark):
    """The query's decision, with n-grams, margins and losses taken one by one."""
    rng = random.Random(4)
    rows = [(i, text(rng, TONGUES[k], rng.randint(5, 40)), k) for i, k in enumerate(list(TONGUES) * 10)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = L.learn(df)
    got = {r["doc_id"]: r for r in L.identify(df, model).collect()}

    def slot(gram):
        code = 0
        for c in gram:
            code = (code * 0x01000193 + c) % 2**32
        x = (code + len(gram)) * 0x9E3779B1 % 2**32
        return ((x >> 13) ^ x) % L.DIM

    for i, t, _ in rows[:12]:
        raw = [c if c > 127 else c | 32 if chr(c).isalpha() else 32 for c in (" " + t + " ").encode()]
        counts = {}
        for n in range(1, 5):
            for k in range(len(raw) - n + 1):
                f = slot(raw[k : k + n])
                counts[f] = counts.get(f, 0) + 1
        size = sum(counts.values()) ** 0.5
        loss = []
        for word in model.code:
            margins = [sum(c**0.5 / size * float(model.w[f, b]) for f, c in counts.items()) + model.c[b] for b in range(len(word))]
            loss.append(sum(w * np.log1p(np.exp(-m * s)) for w, m, s in zip(model.trust, margins, word)) * len(word))
        best = min(range(len(loss)), key=loss.__getitem__)
        p = 1 / sum(np.exp(loss[best] - x) for x in loss)
        assert got[i]["lang_pred"] == model.names[best] and abs(got[i]["score"] - p) < 1e-4


def test_repeated_ids_teach_once(spark):
    rng = random.Random(9)
    base = [(i, text(rng, TONGUES[k], 20), k) for i, k in enumerate(["en", "de"] * 30)]
    again = [(0, text(rng, TONGUES["en"], 20), "en") for _ in range(300)] + [base[1]] * 300
    schema = "doc_id long, text string, lang string"
    seen = []
    original, L.fit_bits = L.fit_bits, lambda x, *rest: seen.append(len(x)) or original(x, *rest)
    try:
        L.learn(spark.createDataFrame(base, schema))
        L.learn(spark.createDataFrame(base + again, schema))
    finally:
        L.fit_bits = original
    assert seen[0] == seen[1]
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(60)], "doc_id long, quality int, toxic int")
    one, two = (Q.learn(spark.createDataFrame(r, schema), labels) for r in (base + base, base))
    assert (one[0] == two[0]).all() and one[1] == two[1]


def test_language_edges(spark):
    schema = "doc_id long, text string, lang string"
    empty = spark.createDataFrame([], schema)
    assert L.learn(empty) is None and L.identify(empty, None).count() == 0
    one = spark.createDataFrame([(i, "some words", "en") for i in range(20)], schema)
    assert {r["lang_pred"] for r in L.identify(one, L.learn(one)).collect()} == {"en"}
    assert {r["lang_pred"] for r in L.identify(one, None).collect()} == {"und"}


def test_codewords_are_apart():
    for k in (2, 3, 4, 5, 9, 40):
        code = L.codewords(k)
        assert code.shape[0] == k and len({tuple(r) for r in code.tolist()}) == k
        assert all(abs(c.sum()) < k for c in code.T)


def test_tokens_by_brute_force():
    rng = random.Random(5)
    texts = [("".join(rng.choice("aB1é%!| \n") for _ in range(rng.randint(0, 60)))).encode() for _ in range(200)] + [b"", b"x" * 300]
    words = linear._Tokens(texts)
    kind = lambda c: 0 if c in b" \t\n\r\x0b\x0c" else 1 if chr(c).isalnum() and c < 128 or c > 127 else 2
    for d, t in enumerate(texts):
        want, k = [], 0
        while k < len(t):
            j = k
            while j < len(t) and kind(t[j]) == kind(t[k]):
                j += 1
            if kind(t[k]):
                want.append(t[k:j])
            k = j
        got = [bytes(words.raw[a:b]) for a, b in zip(words.start[words.ptr[d] : words.ptr[d + 1]], words.end[words.ptr[d] : words.ptr[d + 1]])]
        assert got == want
    ids, ptr = linear.word_ngrams(texts, 1 << 18)
    for d in range(0, 200, 20):
        one, _ = linear.word_ngrams([texts[d]], 1 << 18)
        assert sorted(one) == sorted(ids[ptr[d] : ptr[d + 1]])


def test_words_and_hashes():
    texts = [b"a bb\tc\x0bd", b"", b" \n", b"y" * 200 + b" z", "é x".encode(), b"ab ba"]
    w = C.Words(texts)
    assert [w.ptr[i + 1] - w.ptr[i] for i in range(6)] == [len(t.split()) for t in texts]
    h = w.hashes()
    assert len(set(h.tolist())) == len({x for t in texts for x in t.split()})


def test_ftrl_is_logistic_regression():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(3000, 4))
    y = (rng.random(3000) < linear.sigmoid(x @ [1.5, -1, 0, 0.5] + 0.3)).astype(int)
    model = linear.FTRL(4, alpha=0.2, l1=0.0, l2=0.0)
    for _ in range(5):
        for v, t in zip(x, y):
            model.update(np.arange(4), v, t)
    assert np.allclose(model.weights(), [1.5, -1, 0, 0.5], atol=0.2) and abs(model.intercept() - 0.3) < 0.2
    strong = linear.FTRL(4, l1=1e6)
    strong.update(np.arange(4), x[0], 1)
    assert (strong.weights() == 0).all()


def test_quality_by_brute_force(spark):
    rng = random.Random(12)
    texts = [text(rng, TONGUES["en"], 30) + (" BUY now now!!" if i % 2 else "") for i in range(40)] + ["", "The THE the"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1 - i % 2, 0) for i in range(40)], "doc_id long, quality int, toxic int")
    w, c = Q.learn(docs, labels)
    got = {r["doc_id"]: r["score"] for r in Q.score(docs, (w, c)).collect()}
    for i, t in enumerate(texts):
        counts, tokens = {}, linear._Tokens([t.encode()])
        h = [int(x) for x in tokens.hashes()]
        low = [bytes(tokens.raw[a:b]).lower() for a, b in zip(tokens.start, tokens.end)]
        feats = [x % Q.DIM for x in h]
        feats += [int(C.mix64(np.array([(b * 3 + a) % 2**64], np.uint64))[0]) % Q.DIM for a, b in zip(h, h[1:])]
        feats += [1 for a, b in zip(low, low[1:]) if a == b]
        feats += [2 for a, b in zip(tokens.start, tokens.end) if b - a > 1 and all(65 <= x <= 90 for x in tokens.raw[a:b])]
        for f in feats:
            counts[f] = counts.get(f, 0) + 1
        size = max(sum(counts.values()) ** 0.5, 1e-12)
        margin = sum(n**0.5 / size * float(w[f]) for f, n in counts.items()) + c
        assert abs(got[i] - 1 / (1 + np.exp(-margin))) < 1e-6


def test_quality(spark):
    rng = random.Random(2)
    good = [text(rng, TONGUES["en"], rng.randint(20, 200)) for _ in range(150)]
    bad = [" ".join(w + "%%%" for w in text(rng, TONGUES["en"], 60).split()) for _ in range(150)]
    rows = [(i, t) for i, t in enumerate(x for p in zip(good, bad) for x in p)]
    docs = spark.createDataFrame(rows + [(900, None), (901, ""), (None, "the"), (0, good[0])], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1 - i % 2, 0) for i, _ in rows] + [(2, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    got = Q.score(docs, Q.learn(docs, labels)).collect()
    assert len(got) == 304 and all(0 <= r["score"] <= 1 for r in got)
    assert all((r["score"] >= 0.5) == (r["doc_id"] % 2 == 0) for r in got if r["doc_id"] is not None and r["doc_id"] < 300)
    none = Q.learn(docs, labels.limit(0))
    assert {r["score"] for r in Q.score(docs, none).collect()} == {0.5}
    assert Q.score(docs.limit(0), none).count() == 0
