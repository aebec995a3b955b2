"""A corpus pipeline of five stages over ``documents``: quality rules, near-duplicate
removal, substring dedup, mixing to target weights, SentencePiece encoding.

Every stage is written as Parquet and read again as the next one's documents.  All but the
last return the columns of documents; the last returns the encoded mix.
"""

from __future__ import annotations

import threading

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from curvetide.llm import common as C
from curvetide.llm import mixing, near_dedup, quality_rules, sentencepiece_codec, substring_dedup


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep.  Null and empty texts go; repeated rows are
    judged each; null lang or source is a group of its own; other columns stay."""
    return quality_rules.keep_good(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: five words, similarity 0.8.  That of
    least id stays, with all rows of that id; rows of null id stay; other columns stay."""
    return near_dedup.without_near_duplicates(docs, k=5, percent=80)


def passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the windows of 13 words that an earlier document has.  Rows of one id
    and rows of null id lose nothing to each other; a row that loses every word goes; other
    columns stay as they are (n_chars follows the text)."""
    return substring_dedup.without_repeats(docs, window=13)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix of all sources, a row for each document and pass that takes words of it: ids
    and other columns occur once for each pass.  Empty texts are taken in no pass; null
    source is a source; repeated rows are documents of their own."""
    return mixing.mixed_texts(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, source, n_tokens, ids): a row for each row of the mix, in any order; a null or
    empty text has no ids."""
    import public_tokenizers

    out = sentencepiece_codec.encode(docs.select("doc_id", "source", "text"), public_tokenizers.path("piece_bpe_32k.model"))
    return out.select("doc_id", "source", F.size("ids").alias("n_tokens"), "ids")


_pending = threading.local()  # tables that the last stage of this thread left for its result


def _tidy(stage):
    """A stage's tables in the shared folder go when the next stage of the thread starts: by
    then its result is written.  Tables that the given documents still read stay."""

    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        read = docs.inputFiles()
        C.discard(spark, *[p for p in getattr(_pending, "paths", ()) if not any(p.rsplit("/", 1)[-1] in f for f in read)])
        with C.watched() as _pending.paths:
            return stage(spark, docs, sf_dir)

    run.__name__, run.__doc__ = stage.__name__, stage.__doc__
    return run


STAGES = [(name, _tidy(f)) for name, f in (("quality rules", rules), ("near duplicates", near), ("substring dedup", passages), ("mixing", mixture), ("sentencepiece", tokens))]
ORACLE_SQL = None  # robust estimates, hashing and tokenisation aren't SQL


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = C.materialize(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return docs
