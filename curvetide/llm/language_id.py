"""Language identification with error-correcting output codes.

Each language has a codeword of bits; a binary logistic classifier on hashed byte n-grams
learns each bit.  Decoding weighs the bits' losses: a language's loss is the sum over the
bits of the logistic loss of its own bit values, and the least loss wins.  A small gap to
the second language flags an ambiguous text.

Training reads at most ``SAMPLE`` rows of each language (those of least hash of the id
among rows that aren't held out), a documented bound; every text is scored as a whole.

Edge cases: null text and text without a letter give ``und`` with score 0; rows of null
lang teach nothing; of several texts of an id in one language one teaches, that of least
hash; without a learned language every text is ``und``; a single learned
language is always predicted; repeated rows are scored each; null id counts as held out.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C
from .linear import byte_counts, damped, sigmoid

DIM = 8192
SAMPLE = 400  # training rows of each language, at most
PARTS = 20
_LETTER = regex.compile(r"\p{L}")


def codewords(k: int) -> np.ndarray:
    """k codewords of -1/+1: all splits for few classes, else random ones far apart."""
    if k <= 1:
        return np.ones((k, 1))
    if k <= 5:
        rows = [(1, *r) for r in itertools.product((1, -1), repeat=k - 1)]
        return np.array([r for r in rows if len(set(r)) == 2], float).T
    rng, best, far = np.random.default_rng(5), None, -1
    bits = max(15, 4 * int(np.ceil(np.log2(k))))
    for _ in range(200):
        code = rng.choice([-1.0, 1.0], (k, bits))
        code = code[:, np.abs(code.sum(axis=0)) < k]
        apart = min(((code[a] != code[b]).sum() for a, b in itertools.combinations(range(k), 2)), default=0)
        if apart > far:
            best, far = code, apart
    return best


def fit_bits(x: np.ndarray, t: np.ndarray, weight: np.ndarray, rounds=80, l2=1e-4) -> tuple[np.ndarray, np.ndarray]:
    """Logistic regressions for all bits at once, by accelerated gradient steps.

    t: (rows, bits) of -1/+1."""
    w = np.zeros((x.shape[1], t.shape[1]), np.float32)
    t, weight = t.astype(np.float32), weight.astype(np.float32)
    c = np.zeros(t.shape[1])
    v, vc, lag, lagc = w, c, w, c
    step = 8.0
    for i in range(rounds):
        s = -t * sigmoid(-t * (x @ v + vc)) * weight[:, None]
        lag, lagc, w, c = w, c, v - step * (x.T @ s + l2 * v), vc - step * 0.2 * s.sum(axis=0)
        m = i / (i + 3)
        v, vc = w + m * (w - lag), c + m * (c - lagc)
    return w, c


class CodeModel:
    def __init__(self, names: list[str], code: np.ndarray, w: np.ndarray, c: np.ndarray):
        self.names, self.code, self.w, self.c = names, code, w.astype(np.float32), c
        flat = np.abs(w).mean(axis=0) + 1e-9
        self.trust = flat / flat.sum()

    def losses(self, counts: np.ndarray) -> np.ndarray:
        margin = damped(counts).astype(np.float32) @ self.w + self.c
        each = np.logaddexp(0, -margin[:, None, :] * self.code[None])
        return (each * self.trust).sum(axis=2) * self.code.shape[1]

    def decode(self, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(language, score, gap): the score is the softmax of the negative losses."""
        loss = self.losses(counts)
        p = np.exp(-(loss - loss.min(axis=1, keepdims=True)))
        p /= p.sum(axis=1, keepdims=True)
        best = p.argmax(axis=1)
        top = np.sort(p, axis=1)
        return best, top[:, -1], top[:, -1] - (top[:, -2] if p.shape[1] > 1 else 0.0)


def _features(batches):
    for batch in batches:
        lang = batch.column("lang")
        for a, b, texts in C.text_batches(batch):
            rows = [damped(byte_counts(t, DIM)) for t in texts]
            yield pa.record_batch([lang.slice(a, b - a), pa.array([np.flatnonzero(r).astype(np.uint16).tobytes() for r in rows], pa.binary()), pa.array([r[r > 0].astype(np.float32).tobytes() for r in rows], pa.binary())], names=["lang", "f", "v"])


def learn(docs: DataFrame) -> CodeModel | None:
    """Fit on a bounded sample of rows (doc_id, text, lang) that aren't held out."""
    from pyspark.sql import Window

    # by parts of a language, so that no task gets a whole language; of an id's texts in a
    # language that of least hash teaches, so that rows are bounded, not only ids
    rank = F.row_number().over(Window.partitionBy("lang", "part").orderBy(F.xxhash64("doc_id"), "doc_id"))
    pool = docs.where(~C.held_out(F.col("doc_id")) & F.col("lang").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), "lang", "text")
    part = F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(PARTS)).alias("part")
    chosen = pool.select("doc_id", "lang", part).distinct().withColumn("r", rank).where(F.col("r") <= SAMPLE // PARTS).select("doc_id", "lang")
    rows = pool.join(F.broadcast(chosen), ["doc_id", "lang"]).groupBy("doc_id", "lang").agg(F.min_by("text", F.xxhash64("text")).alias("text"))
    rows = rows.select("lang", "text").mapInArrow(_features, "lang string, f binary, v binary").collect()
    if not rows:
        return None
    names = sorted({r["lang"] for r in rows})
    y = np.array([names.index(r["lang"]) for r in rows])
    x = np.zeros((len(rows), DIM), np.float32)
    for i, r in enumerate(rows):
        x[i, np.frombuffer(r["f"], np.uint16)] = np.frombuffer(r["v"], np.float32)
    code = codewords(len(names))
    if len(names) == 1:
        return CodeModel(names, code, np.zeros((DIM, 1)), np.full(1, 10.0))
    share = 1.0 / (np.bincount(y)[y] * len(names))
    w, c = fit_bits(x, code[y], share)
    return CodeModel(names, code, w, c)


def _score(sent):
    def run(batches):
        model = sent.value
        for batch in batches:
            ids = batch.column("doc_id")
            for a, b, texts in C.text_batches(batch):
                live = [i for i, t in enumerate(texts) if _LETTER.search(t.decode("utf-8", "replace"))] if model else []
                name, score, gap = ["und"] * len(texts), [0.0] * len(texts), [0.0] * len(texts)
                if live:
                    best, top, apart = model.decode(np.stack([byte_counts(texts[i], DIM) for i in live]))
                    for i, k, s, g in zip(live, best.tolist(), top.tolist(), apart.tolist()):
                        name[i], score[i], gap[i] = model.names[k], s, g
                yield pa.record_batch([ids.slice(a, b - a), pa.array(name), pa.array(score), pa.array(gap)], names=["doc_id", "lang_pred", "score", "gap"])

    return run


def identify(docs: DataFrame, model: CodeModel | None, unsure: float = 0.2) -> DataFrame:
    """(doc_id, lang_pred, score, ambiguous) of each row (doc_id, text)."""
    C.need(docs, "doc_id", "text")
    sent = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_score(sent), "doc_id long, lang_pred string, score double, gap double")
    return rows.select("doc_id", "lang_pred", "score", (F.col("gap") < unsure).alias("ambiguous"))


def op6_language_id(spark, sf_dir: str) -> DataFrame:
    model = learn(C.read_table(spark, sf_dir, "documents", "doc_id", "text", "lang"))
    out = identify(C.read_table(spark, sf_dir, "documents", "doc_id", "text"), model)
    return out.select("doc_id", C.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "ambiguous")
