"""Shared pieces of the corpus operators: words, hashes, tables in the shared folder.

Words are maximal runs of bytes outside ``\\x20\\x09-\\x0D``; ``bytes.split()`` uses
exactly that set of separators, so splitting UTF-8 bytes gives the contract's words.
"""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager
from contextvars import ContextVar

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType

WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"
BATCH_BYTES = 2 << 20  # of text that one vectorised step takes

_U = np.uint64


# ------------------------------------------------------------------ shared folder
def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where it isn't set, a local session (tests) gets a temporary folder; on a cluster, where
    such a folder would be another one on each machine, this is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="curvetide-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/curvetide/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write ``df`` to the shared folder and read it again."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    note(path)
    return spark.read.schema(df.schema).parquet(path)


_open: ContextVar[tuple[list[str], ...]] = ContextVar("curvetide_scratch", default=())


def note(path: str) -> None:
    """Let the innermost open scratch delete ``path`` at its end."""
    if _open.get():
        _open.get()[-1].append(path)


@contextmanager
def watched():
    """The list of the tables that are written inside the block and outlive it."""
    paths: list[str] = []
    token = _open.set((*_open.get(), paths))
    try:
        yield paths
    finally:
        _open.reset(token)


class Scratch:
    """``with Scratch(spark) as tables: ...; return tables.keep(df)``

    Tables written inside the block are deleted at its end.  ``keep`` writes its frame as a
    table that outlives the block (it then belongs to the scratch around, if any).  Each
    thread and each block has its own list."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths, self.kept = spark, [], []

    def __enter__(self) -> Scratch:
        self._token = _open.set((*_open.get(), self.paths))
        return self

    def keep(self, df: DataFrame, name: str = "result") -> DataFrame:
        out = materialize(df, name)
        self.kept.append(self.paths.pop())
        return out

    def __exit__(self, *error) -> None:
        _open.reset(self._token)
        discard(self.spark, *self.paths)
        for path in self.kept:
            note(path)


def discard(spark: SparkSession, *paths: str) -> None:
    """Delete tables of the shared folder that nothing reads any more."""
    jvm = spark.sparkContext._jvm
    for p in paths:
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def need(df: DataFrame, *columns: str) -> None:
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")


# ------------------------------------------------------------------ Column helpers
def word_count(text: Column) -> Column:
    """Number of words; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def held_out(doc_id: Column) -> Column:
    """True where crc32 of the id as text leaves 2 modulo 4 (null id: held out)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(True))


# ------------------------------------------------------------------ vectorised hashing
def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective mixing of 64-bit words (the splitmix64 finaliser)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> _U(30)
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def stream64(n: int, seed: int) -> np.ndarray:
    """n fixed pseudorandom 64-bit words."""
    return mix64((np.arange(1, n + 1, dtype=np.uint64) + _U(seed << 20)) * _U(0x9E3779B97F4A7C15))


_BYTE_AT = stream64(256 * 64, 7)
_SHIFT = stream64(64, 11) | _U(1)
_GAP = np.zeros(256, bool)
_GAP[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


class Words:
    """The words of a run of documents, as offsets into one buffer.

    ``start``/``end``: byte offsets; ``ptr[d]:ptr[d + 1]``: the words of document d."""

    def __init__(self, texts: list[bytes], lower: bool = False):
        buf = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8) if texts else np.zeros(0, np.uint8)
        self.buf = _LOWER[buf] if lower else buf
        gap = _GAP[buf]
        edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1 if len(buf) else np.zeros(0, np.int64)
        if len(buf) and not gap[0]:
            edge = np.concatenate([[0], edge])
        self.start, self.end = edge[0::2], edge[1::2]
        bounds = np.cumsum([0] + [len(t) + 1 for t in texts])
        self.ptr = np.searchsorted(self.start, bounds)

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of each word: sum of a random value for each (byte, place)."""
        if not len(self.start):
            return np.zeros(0, np.uint64)
        size = self.end - self.start
        first = np.concatenate([[0], np.cumsum(size)[:-1]])
        keep = np.repeat(self.start - first, size)
        keep += np.arange(len(keep))
        at = keep - np.repeat(self.start, size)
        value = _BYTE_AT[(self.buf[keep].astype(np.int64) << 6) | (at & 63)]
        if size.max() > 64:
            far = at >= 64
            value[far] *= (2 * (at[far] >> 6) + 1).astype(np.uint64)
        return mix64(np.add.reduceat(value, first) ^ size.astype(np.uint64))


def window_hashes(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all k consecutive items of h; empty if there are fewer."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(k):
        out += h[j : j + n] * _SHIFT[j]
    return mix64(out)


def encoded(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


def runs(sizes, limit: int = BATCH_BYTES):
    """Slices of consecutive items of at most ``limit`` in sum (one item at least)."""
    a, total = 0, 0
    for i, s in enumerate(sizes):
        if i > a and total + s > limit:
            yield a, i
            a, total = i, 0
        total += s
    if a < len(sizes):
        yield a, len(sizes)


def text_batches(batch, column: str = "text", limit: int = BATCH_BYTES):
    """Slices (a, texts as bytes) of an Arrow batch, by the bytes of their texts."""
    col = batch.column(column)
    sizes = [0 if s is None else s for s in _byte_sizes(col)]
    for a, b in runs(sizes, limit):
        yield a, b, [encoded(t) for t in col.slice(a, b - a).to_pylist()]


def _byte_sizes(col):
    import pyarrow.compute as pc

    return pc.binary_length(col).to_pylist()


# ------------------------------------------------------------------ components
def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Connected components by repeated contraction: (node, component = its least node).

    Each round every node joins the neighbour of least hash (drawn anew each round), and
    the edges between the merged nodes form the next, smaller graph; the expected number
    of rounds is logarithmic.  Every round is a table of the shared folder.  A hub's edges
    are aggregated before they meet, and joins on it are left to the adaptive skew split.
    Nodes may be of any type with an order; those without an edge aren't returned."""
    spark = edges.sparkSession
    node = edges.schema[a].dataType
    with Scratch(spark) as tables:
        todo = materialize(edges.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a <> b").distinct(), "edges")
        steps: list[DataFrame] = []
        while not todo.isEmpty():
            rnd = len(steps)
            rank = F.xxhash64(F.lit(rnd), F.col("b"))
            both = todo.union(todo.select(F.col("b").alias("a"), F.col("a").alias("b")))
            step = both.groupBy("a").agg(F.min(F.struct(rank.alias("r"), F.col("b"))).alias("m"))
            own = F.xxhash64(F.lit(rnd), F.col("a"))
            step = materialize(step.select(F.col("a").alias("node"), F.when(own < F.col("m.r"), F.col("a")).otherwise(F.col("m.b")).alias("to")), f"hook{rnd}")
            steps.append(step)
            x = todo.join(step.withColumnRenamed("node", "a"), "a").select(F.col("to").alias("x"), "b")
            y = x.join(step.withColumnRenamed("node", "b"), "b").select("x", F.col("to").alias("y"))
            todo = materialize(y.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), f"edges{rnd}")
        if not steps:
            return spark.createDataFrame([], StructType([StructField("node", node), StructField("component", node)]))
        label = steps[0]
        for nxt in steps[1:]:
            nxt = nxt.select(F.col("node").alias("to"), F.col("to").alias("up"))
            label = label.join(nxt, "to", "left").select("node", F.coalesce("up", "to").alias("to"))
        label = materialize(label, "labels")
        least = label.groupBy("to").agg(F.min("node").alias("component"))
        return tables.keep(label.join(least, "to").select("node", "component"), "components")
