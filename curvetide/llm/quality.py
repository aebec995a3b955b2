"""Quality classifier: hashed word n-gram logistic regression learned by FTRL.

Features are hashed 1- and 2-grams of the tokens of the whole text, weighed by damped
counts; a score is the sigmoid of a sparse dot product.  Learning takes at most ``SAMPLE``
labelled rows (those of least hash of the id among rows that aren't held out), a documented
bound, in an order drawn from the ids, and passes over them ``EPOCHS`` times.

Edge cases: null and empty texts score by the intercept; labels of null quality teach
nothing; a document labelled twice teaches twice; of several texts of an id one teaches,
that of least hash; without labels every score is 0.5; null
id counts as held out.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C
from .linear import FTRL, sigmoid, sparse_rows, word_ngrams

DIM = 1 << 18
SAMPLE = 4000
EPOCHS = 3
CUT = 0.7


def _features(batches):
    for batch in batches:
        y, key = batch.column("quality"), batch.column("key")
        for a, b, texts in C.text_batches(batch):
            rows = sparse_rows(*word_ngrams(texts, DIM))
            yield pa.record_batch([key.slice(a, b - a), y.slice(a, b - a), pa.array([f.astype(np.int32).tobytes() for f, _ in rows], pa.binary()), pa.array([v.astype(np.float32).tobytes() for _, v in rows], pa.binary())], names=["key", "quality", "f", "v"])


def learn(docs: DataFrame, labels: DataFrame) -> tuple[np.ndarray, float]:
    """Weights and intercept from (doc_id, text) and (doc_id, quality)."""
    C.need(docs, "doc_id", "text")
    C.need(labels, "doc_id", "quality")
    known = labels.where("quality IS NOT NULL AND doc_id IS NOT NULL").where(~C.held_out(F.col("doc_id"))).select("doc_id", F.col("quality").cast("int").alias("quality"))
    chosen = known.withColumn("key", F.xxhash64(F.lit("quality"), "doc_id")).orderBy("key", "doc_id", "quality").limit(SAMPLE)
    # of an id's texts that of least hash teaches, so that rows are bounded, not only ids
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen.select(F.col("doc_id").cast("long").alias("doc_id")).distinct()), "doc_id")
    texts = texts.groupBy("doc_id").agg(F.min_by(F.coalesce("text", F.lit("")), F.xxhash64("text")).alias("text"))
    rows = texts.join(F.broadcast(chosen), "doc_id").select("key", "quality", "text").mapInArrow(_features, "key long, quality int, f binary, v binary").collect()
    model = FTRL(DIM)
    rows.sort(key=lambda r: (r["key"], r["quality"], r["f"]))
    data = [(np.frombuffer(r["f"], np.int32), np.frombuffer(r["v"], np.float32).astype(float), int(r["quality"] == 1)) for r in rows]
    ones = sum(y for _, _, y in data)
    weight = {1: 1.0, 0: min(1.5, max(1.0, ones / max(1, len(data) - ones)))}
    for _ in range(EPOCHS if len({y for _, _, y in data}) > 1 else 1):
        for f, v, y in data:
            model.update(f, v, y, weight[y])
    return model.weights().astype(np.float32), float(model.intercept())


def _score(sent):
    def run(batches):
        w, c = sent.value
        for batch in batches:
            ids = batch.column("doc_id")
            for a, b, texts in C.text_batches(batch):
                rows = sparse_rows(*word_ngrams(texts, DIM))
                s = sigmoid(np.array([float(w[f] @ v) for f, v in rows]) + c)
                yield pa.record_batch([ids.slice(a, b - a), pa.array(s)], names=["doc_id", "score"])

    return run


def score(docs: DataFrame, model: tuple[np.ndarray, float]) -> DataFrame:
    """(doc_id, score) of each row (doc_id, text)."""
    C.need(docs, "doc_id", "text")
    sent = docs.sparkSession.sparkContext.broadcast(model)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_score(sent), "doc_id long, score double")


def op10_quality_classifier(spark, sf_dir: str) -> DataFrame:
    docs = C.read_table(spark, sf_dir, "documents", "doc_id", "text")
    model = learn(docs, C.read_table(spark, sf_dir, "labels", "doc_id", "quality"))
    return score(docs, model).select("doc_id", C.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))
