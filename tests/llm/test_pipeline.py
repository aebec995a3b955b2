import random

import corpus_pipeline as P
from curvetide.llm import common as C
from curvetide.llm import queries as R


def rows(n=120):
    rng = random.Random(8)
    vocab = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(3, 8))) for _ in range(3000)]
    out = [(i, " ".join(rng.choice(vocab) for _ in range(rng.randint(60, 160))), "en", f"s{i % 3}", None) for i in range(n)]
    passage = " ".join(rng.choice(vocab) for _ in range(60))
    out += [(200, out[3][1], "en", "s0", None), (201, out[4][1] + " tail", "en", "s1", None), (202, out[5][1] + " " + passage, "en", "s1", None), (203, passage + " " + out[6][1][::-1], "en", None, None)]
    return out + [(300, None, None, None, None), (301, "", "en", "s0", 0), (302, "a b c d e " * 50, "en", "s0", None)], passage


def test_stages(spark, table):
    data, passage = rows()
    sf = table(documents=spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long"))
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, []
    for name, stage in P.STAGES:
        docs = C.materialize(stage(spark, docs, sf), "test-stage")
        seen.append(docs)
        if name != P.STAGES[-1][0]:
            assert docs.columns == columns
    ids = [{r["doc_id"] for r in d.select("doc_id").distinct().collect()} for d in seen]
    assert set(range(120)) <= ids[0] and not ids[0] & {300, 301, 302}
    assert ids[1] == ids[0] - {200, 201}
    text = {r["doc_id"]: r["text"] for r in seen[2].collect()}
    assert passage in text[202] and passage not in text[203]
    assert seen[4].count() == seen[3].count() and all(r["n_tokens"] == len(r["ids"]) > 0 for r in seen[4].collect())
    assert P.run(spark, sf).count() == seen[4].count()


def test_stages_by_brute_force(spark, table):
    """Each stage's rows from its own input: kept ids, cut texts, words of the mix, ids."""
    import public_tokenizers
    import sentencepiece
    from pyspark.sql import functions as F
    from test_near import brute as near
    from test_substring import brute as cut

    data, _ = rows(60)
    sf = table(documents=spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long").withColumn("at", F.expr("timestamp'2024-02-03 04:05:06.123456' + make_interval(0, 0, 0, doc_id)")))
    docs, seen = spark.read.parquet(f"{sf}/documents.parquet"), []
    at = {r["doc_id"]: r["at"] for r in docs.collect()}
    for name, stage in P.STAGES:
        docs = C.materialize(stage(spark, docs, sf), "brute-stage")
        seen.append(docs.collect())
    rules, apart, passages, mix, ids = seen
    assert all(r["at"] == at[r["doc_id"]] and r["at"].microsecond == 123456 for s in seen[:4] for r in s)
    text = {r["doc_id"]: r["text"] for r in rules}
    assert {r["doc_id"] for r in apart} == {i for i, (_, _, kept) in near(list(text.items()), 5, 80).items() if kept}
    want = {i: kept for i, _, _, kept in cut([(r["doc_id"], r["text"]) for r in apart])}
    assert {r["doc_id"]: " ".join(r["text"].split()) for r in passages} == {i: t for i, t in want.items() if t}
    words = {r["doc_id"]: r["text"].split() for r in passages}
    sizes = {}
    for r in passages:
        sizes[r["source"]] = sizes.get(r["source"], 0) + len(words[r["doc_id"]])
    got = dict.fromkeys(sizes, 0)
    for r in mix:
        part = iter(words[r["doc_id"]])
        assert all(w in part for w in r["text"].split())  # words of the document, in order
        got[r["source"]] += len(r["text"].split())
    from test_mixing import expected_targets

    assert all(abs(got[s] - t) <= 0.5 for s, t in expected_targets(sizes).items())
    library = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    assert sorted((r["doc_id"], tuple(r["ids"])) for r in ids) == sorted((r["doc_id"], tuple(library.encode(r["text"]))) for r in mix)


def test_empty_documents(spark, table):
    sf = table(documents=spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long"))
    assert P.run(spark, sf).count() == 0


def test_registered():
    names = set(R.queries())
    assert sorted(int(n[2:].split("_")[0]) for n in names) == list(range(1, 11))
