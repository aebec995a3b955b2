"""Design matrices: DataFrames of (row_id, y, x) with a known number of features."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import columns as X
from ..functions.hashing import P, coefficients, hash_of, powers, uniform_col
from . import tables


@dataclass
class DesignMatrix:
    """Examples (row_id BIGINT, y DOUBLE or INT, x ARRAY<DOUBLE> of length d)."""

    df: DataFrame
    d: int
    classes: int = 0
    blocks: DataFrame | None = None  # the same rows as ``vectors.packed`` has them, or with ``drawn`` only their ids
    laid: int = 0  # rows of one of so many workers lie one behind the other in one partition of ``blocks``
    tasks: int = 0  # partitions of ``blocks``
    passes: object = None  # shares passes over ``blocks`` between fits (``optimise.Passes``)
    ids: DataFrame | None = None  # (row_id) of rows that are functions of their ids
    drawn: Callable | None = None  # (y, x) of an array of these ids

    def validate(self) -> None:
        """Fails on ragged or non-finite rows, nulls, and repeated row ids.

        Two rows of one id would share bucket and sign in every sketch block, which biases
        the sketched Gram matrix; so ids must be unique."""
        bad = F.col("x").isNull() | F.col("row_id").isNull() | F.col("y").isNull() | (F.size("x") != self.d)
        bad = bad | F.exists("x", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
        row = self.df.agg(F.count_if(bad).alias("bad"), F.count(F.lit(1)).alias("n")).collect()[0]
        if row["bad"]:
            raise ValueError(f"{row['bad']} rows are null, ragged or not finite")
        twice = self.df.groupBy("row_id").count().where("count > 1").limit(1).collect()
        if twice:
            raise ValueError(f"row_id {twice[0]['row_id']} occurs {twice[0]['count']} times")

    def split(self, parts: int = 4) -> tuple[DesignMatrix, DesignMatrix]:
        """(train, test): one of ``parts`` hash parts is the test part."""
        test = F.pmod(F.xxhash64("row_id"), F.lit(parts)) == 0
        return DesignMatrix(self.df.where(~test), self.d, self.classes), DesignMatrix(self.df.where(test), self.d, self.classes)

    def head(self, d: int) -> DesignMatrix:
        """The first d features."""
        return DesignMatrix(self.df.withColumn("x", F.slice("x", 1, d)), d, self.classes)


def clean(df: DataFrame, on_null: str = "error") -> DataFrame:
    """Null and NaN features: an error at run time, zeros, or dropped rows."""
    wrong = lambda v: v.isNull() | F.isnan(v)
    if on_null == "zero":
        return df.withColumn("x", F.transform("x", lambda v: F.when(wrong(v), 0.0).otherwise(v)))
    if on_null == "drop":
        return df.where(F.col("y").isNotNull() & ~F.exists("x", wrong))
    if on_null != "error":
        raise ValueError(on_null)
    return df.withColumn("x", F.transform("x", lambda v: F.when(wrong(v), F.raise_error(F.lit("null or NaN feature")).cast("double")).otherwise(v)))


def embeddings(spark: SparkSession, sf_dir: str) -> DesignMatrix:
    """Binary task on the embedding vectors: +1 for labels below 5."""
    df = tables.table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    y = F.when(F.col("label") < 5, 1.0).otherwise(-1.0)
    return DesignMatrix(df.select(F.col("vec_id").alias("row_id"), y.alias("y"), F.col("embedding").cast("array<double>").alias("x")), 64)


def embeddings_multi(spark: SparkSession, sf_dir: str) -> DesignMatrix:
    df = tables.table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    return DesignMatrix(df.select(F.col("vec_id").alias("row_id"), F.col("label").cast("double").alias("y"), F.col("embedding").cast("array<double>").alias("x")), 64, 10)


LINE_KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice"]


def line_id() -> Column:
    """A 61-bit id from the six columns that tell order lines apart."""
    return F.xxhash64(*LINE_KEY).bitwiseAND(F.lit((1 << 61) - 1))


def uniform_features(row_id: Column, d: int, seed: int = 1) -> Column:
    """d features uniform in [-1, 1), drawn from the row id."""
    return F.array(*[uniform_col(row_id, seed, i) * 2.0 - 1.0 for i in range(d)])


def planted_weights(d: int, seed: int = 2) -> list[float]:
    """d + 1 fixed normal numbers: weights and a bias."""
    return np.random.default_rng(seed).normal(size=d + 1).tolist()


def planted_label(margin: Column, row_id: Column, seed: int = 3) -> Column:
    """+1 with the logistic probability of the margin, by a hash-uniform."""
    return F.when(uniform_col(row_id, seed, 999) < X.sigmoid(margin), 1.0).otherwise(-1.0)


def synthetic(spark: SparkSession, sf_dir: str, d: int = 60, bias: bool = True, place=lambda ids: ids) -> DesignMatrix:
    """The synthetic logistic task: one example for each order line, planted labels.

    ``place`` may exchange and sort the ids before features are drawn from them."""
    ids = place(tables.table(spark, sf_dir, "lineitem", *LINE_KEY).select(line_id().alias("row_id")))
    w = planted_weights(d)

    def drawn(i):
        of, x, margin = powers(i), np.empty((d, len(i))), np.full(len(i), 0.0)
        for k in range(d):  # as ``uniform_features``, ``X.dot`` and ``planted_label`` have it
            x[k] = hash_of(of, coefficients(1, k)) / float(P) * 2.0 - 1.0
            margin += x[k] * w[k]
        e = np.exp(-np.abs(margin + (w[d] if bias else 0.0)))
        p = np.where(margin + (w[d] if bias else 0.0) >= 0, 1 / (1 + e), e / (1 + e))
        return np.where(hash_of(of, coefficients(3, 999)) / float(P) < p, 1.0, -1.0), np.ascontiguousarray(x.T)

    def draw(batches):
        for batch in batches:
            y, x = drawn(batch.column("row_id").to_numpy())
            rows = pa.ListArray.from_arrays(pa.array(np.arange(len(y) + 1) * d, pa.int32()), pa.array(x.reshape(-1)))
            yield pa.record_batch([batch.column("row_id"), pa.array(y), rows], names=["row_id", "y", "x"])

    return DesignMatrix(ids.mapInArrow(draw, "row_id long, y double, x array<double>"), d, ids=ids, drawn=drawn)


# ------------------------------------------------------------------ encoders
def one_hot(column: Column, levels: list) -> list[Column]:
    """0/1 columns for all levels but the first."""
    return [F.when(column == F.lit(v), 1.0).otherwise(0.0) for v in levels[1:]]


FACTORS = {
    "l_returnflag": ["A", "N", "R"],
    "l_linestatus": ["F", "O"],
    "o_orderstatus": ["F", "O", "P"],
    "o_orderpriority": ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"],
    "c_mktsegment": ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"],
}


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with the columns of their order, customer, part and nation.  Dimension
    tables are broadcast by Spark where their size allows."""
    t = lambda n, *c: tables.table(spark, sf_dir, n, *c)
    lines = t("lineitem", *LINE_KEY, "l_discount", "l_tax", "l_returnflag", "l_linestatus")
    orders = t("orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "o_totalprice")
    parts = t("part", "p_partkey", "p_brand", "p_type", "p_size", "p_retailprice")
    cust = t("customer", "c_custkey", "c_nationkey", "c_mktsegment")
    nation = t("nation", "n_nationkey", "n_regionkey")
    out = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return out.join(cust, F.col("o_custkey") == F.col("c_custkey")).join(nation, F.col("c_nationkey") == F.col("n_nationkey"))


def tabular(spark: SparkSession, sf_dir: str, factors: dict | None = None, place=lambda rows: rows) -> DesignMatrix:
    """One-hot factors of the star join, with planted labels.

    ``place`` may exchange and sort the joined rows before features are made of them."""
    rows = place(star(spark, sf_dir).withColumn("row_id", line_id()))
    cols = [c for name, levels in (factors or FACTORS).items() for c in one_hot(F.col(name), levels)]
    cols += one_hot(F.col("n_regionkey"), list(range(5))) + one_hot((F.col("l_discount") * 100).cast("int"), list(range(11)))
    cols += one_hot(F.floor((F.col("p_size") - 1) / 5).cast("int"), list(range(10))) + one_hot(F.col("n_nationkey"), list(range(25)))
    cols += one_hot(F.col("p_brand"), [f"Brand#{i}" for i in range(1, 26)])
    d = len(cols)
    w = planted_weights(d, 5)
    df = rows.select("row_id", F.array(*cols).alias("x"))
    return DesignMatrix(df.select("row_id", planted_label(X.dot(F.col("x"), X.weights(w[:d])), F.col("row_id"), 6).alias("y"), "x"), d)


def numeric(spark: SparkSession, sf_dir: str) -> DesignMatrix:
    """Six scaled numeric columns of lines and parts, with a planted real response."""
    lines = tables.table(spark, sf_dir, "lineitem", *LINE_KEY, "l_discount", "l_tax")
    parts = tables.table(spark, sf_dir, "part", "p_partkey", "p_size", "p_retailprice")
    rows = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).withColumn("row_id", line_id())
    x = [F.col("l_quantity") / 50.0, F.col("l_discount") * 10.0, F.col("l_tax") * 10.0, F.col("p_size") / 50.0, F.col("p_retailprice") / 1000.0, F.col("l_extendedprice") / 50000.0]
    x = [c.cast("double") for c in x]
    noise = uniform_col(F.col("l_orderkey"), 8, 1) - 0.5
    y = x[0] * 1.5 - x[1] * 0.5 + x[2] * 0.25 + x[3] - x[4] * 0.75 + x[5] * 2.0 + noise
    return DesignMatrix(rows.select("row_id", y.alias("y"), F.array(*x).alias("x")), len(x))


def doc_terms(spark: SparkSession, sf_dir: str, d: int = 50, target: str = "quality", idf: bool = False) -> DesignMatrix:
    """Hashed term frequencies of labelled documents, of unit length; +1 for target 1.

    With ``idf`` counts are weighed by one more than the logarithm of all documents over
    those that have the slot; else their roots are taken."""
    docs = tables.table(spark, sf_dir, "documents", "doc_id", "text")
    labels = tables.table(spark, sf_dir, "labels", "doc_id", target)
    words = F.filter(F.split(F.lower("text"), r"[\x20\x09-\x0D]+"), lambda t: t != "")
    slot = F.transform(words, lambda t: F.pmod(F.crc32(t.cast("binary")), F.lit(d)))
    long = docs.join(labels, "doc_id").select("doc_id", F.when(F.col(target) == 1, 1.0).otherwise(-1.0).alias("y"), F.explode(slot).alias("i"))
    tf = long.groupBy("doc_id", "y", "i").agg(F.count(F.lit(1)).alias("n"))
    if idf:
        total = F.broadcast(tf.agg(F.countDistinct("doc_id").alias("docs")))
        rare = tf.groupBy("i").agg(F.count(F.lit(1)).alias("with")).crossJoin(total)
        tf = tf.join(F.broadcast(rare.select("i", (F.log((1 + F.col("docs")) / (1 + F.col("with"))) + 1).alias("idf"))), "i")
        tf = tf.withColumn("v", F.col("n") * F.col("idf"))
    else:
        tf = tf.withColumn("v", F.sqrt("n"))
    row = tf.groupBy("doc_id", "y").agg(F.map_from_entries(F.collect_list(F.struct(F.col("i").cast("int"), "v"))).alias("m"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("len"))
    x = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0)) / F.col("len"))
    return DesignMatrix(row.select(F.col("doc_id").alias("row_id"), "y", x.alias("x")), d)


def brand_program(spark: SparkSession, sf_dir: str) -> tuple[DesignMatrix, list[float]]:
    """A linear program over the brands: rows a x <= b and costs c.

    Suppliers' load shares per brand sum to 1 and are capped by 1; each variable lies
    between 0 and 3; costs are minus the brand's mean retail price in thousands."""
    lines = tables.table(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_quantity")
    parts = tables.table(spark, sf_dir, "part", "p_partkey", "p_brand", "p_retailprice")
    brands = [f"Brand#{i}" for i in range(1, 26)]
    load = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).groupBy("l_suppkey").pivot("p_brand", brands).agg(F.sum("l_quantity"))
    values = F.array(*[F.coalesce(F.col(f"`{b}`"), F.lit(0.0)).cast("double") for b in brands])
    load = load.select(F.col("l_suppkey").cast("long").alias("row_id"), values.alias("v"))
    total = F.aggregate("v", F.lit(0.0), lambda a, b: a + b)
    rows = load.select("row_id", F.lit(1.0).alias("y"), F.transform("v", lambda t: t / total).alias("x"))
    n = len(brands)
    box = spark.range(2 * n).select((F.col("id") + 10**9).alias("row_id"), F.when(F.col("id") < n, 3.0).otherwise(0.0).alias("y"), F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.when(F.col("id") == i, 1.0).when(F.col("id") == i + n, -1.0).otherwise(0.0)).alias("x"))
    price = parts.groupBy("p_brand").agg(F.avg("p_retailprice").alias("p")).collect()
    cost = {r["p_brand"]: -r["p"] / 1000.0 for r in price}
    return DesignMatrix(rows.unionByName(box), n), [cost.get(b, 0.0) for b in brands]
