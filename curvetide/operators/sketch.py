"""The redundant block count-sketch, and other subspace embeddings.

A sketch of N + e blocks of b buckets each: in every block each row has one bucket and one
sign, drawn by hash.  Any N blocks suffice; divided by the number of blocks used, the sum of
their Gram matrices estimates the Gram matrix without bias.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import coefficients, hash_col, hash_np, uniform_np
from .vectors import matrix, pack, sum_packed


@dataclass(frozen=True)
class BlockSketch:
    n: int  # blocks that are needed
    spare: int
    width: int  # buckets of a block
    seed: int = 0

    @property
    def blocks(self) -> int:
        return self.n + self.spare

    @staticmethod
    def of(m: int, width: int, zeta: float = 0.0, spare: int | None = None, seed: int = 0) -> BlockSketch:
        """Sketch size m in blocks of ``width``, with a share zeta (or a number) of spares."""
        n = max(1, math.ceil(m / width))
        return BlockSketch(n, math.ceil(zeta * n) if spare is None else spare, width, seed)

    @staticmethod
    def plan(d: int, multiple: float = 10, memory: int = 128 << 20, straggler_rate: float = 0.02, seed: int = 0) -> BlockSketch:
        """m from d, the width from a worker's memory (two blocks b x b and their product),
        spares from the share of slow workers, doubled."""
        width = max(1, min(d, int(math.sqrt(memory / 24))))
        return BlockSketch.of(int(multiple * d), width, 2 * straggler_rate, seed=seed)

    @staticmethod
    def from_theory(d: int, eps: float, mu: float = 0.1, c1: float = 1.0, c2: float = 1.0, seed: int = 0) -> BlockSketch:
        """Total size c1 d^(1+mu) / eps^2 in c2 / eps blocks."""
        blocks = max(2, math.ceil(c2 / eps))
        return BlockSketch(blocks - 1, 1, max(1, math.ceil(c1 * d ** (1 + mu) / eps**2 / blocks)), seed)

    def fresh(self, it: int) -> BlockSketch:
        """An independent draw for iteration ``it``."""
        return BlockSketch(self.n, self.spare, self.width, self.seed * 1009 + it + 1)

    def grown(self, factor: float) -> BlockSketch:
        return BlockSketch(math.ceil(self.n * factor), math.ceil(self.spare * factor), self.width, self.seed)

    def coef(self, block: int) -> tuple[int, ...]:
        return coefficients(self.seed + 7, block)

    def place_np(self, ids: np.ndarray, block: int) -> tuple[np.ndarray, np.ndarray]:
        h = hash_np(ids, self.coef(block))
        return (h // 2) % self.width, 1.0 - 2.0 * (h % 2)

    # -------------------------------------------------------------- SQL form
    def placed(self, df: DataFrame, blocks: list[int] | None = None) -> DataFrame:
        """``df`` (row_id, ...) once for each block, with block, bucket and sign.  Only the
        blocks asked for are unfolded, so a survivor filter costs nothing below it."""
        use = range(self.blocks) if blocks is None else blocks
        table = F.array(*[F.struct(F.lit(k).alias("block"), *[F.lit(c).cast("long").alias(f"c{j}") for j, c in enumerate(self.coef(k))]) for k in use])
        rows = df.withColumn("_k", F.explode(table))
        h = hash_col(F.col("row_id"), [F.col(f"_k.c{j}") for j in range(7)])
        rows = rows.withColumn("_h", h).withColumn("block", F.col("_k.block"))
        half = (F.col("_h") - F.col("_h") % 2) / 2
        return rows.withColumns({"bucket": (half.cast("long") % self.width).cast("int"), "sign": (1 - 2 * (F.col("_h") % 2)).cast("int")}).drop("_k", "_h")

    def apply_sql(self, df: DataFrame, blocks: list[int] | None = None) -> DataFrame:
        """(block, bucket, i, v) of root rows (row_id, x), in JVM operators."""
        long = self.placed(df.select("row_id", "x"), blocks).select("block", "bucket", "sign", F.posexplode("x").alias("i", "v"))
        return long.groupBy("block", "bucket", "i").agg(F.sum(F.col("sign") * F.col("v")).alias("v"))

    # -------------------------------------------------------------- Arrow form
    def slabs(self, into: dict[int, np.ndarray]):
        """The buffers cut in pieces of about a megabyte: (block, piece, rows)."""
        for k, buf in into.items():
            step = max(1, (1 << 20) // (8 * buf.shape[1]))
            for j, lo in enumerate(range(0, len(buf), step)):
                if buf[lo : lo + step].any():
                    yield k, j, buf[lo : lo + step].reshape(-1)

    def scatter(self, ids: np.ndarray, rows: np.ndarray, into: dict[int, np.ndarray], blocks) -> None:
        if not len(ids):
            return
        sorted_rows = np.empty_like(rows)  # for all blocks, as fresh memory costs more than the sums
        for k in blocks:
            bucket, sign = self.place_np(ids, k)
            slot = 2 * bucket + (sign < 0)  # rows of one bucket and sign are summed as they are
            order = np.argsort(slot.astype(np.int16) if 2 * self.width < 1 << 15 else slot, kind="stable")  # short integers by radix
            s = slot[order]
            head = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
            np.take(rows, order, axis=0, out=sorted_rows, mode="clip")
            sums = np.add.reduceat(sorted_rows, head, axis=0)
            sums[s[head] % 2 == 1] *= -1
            np.add.at(into[k], s[head] // 2, sums)

    def apply_arrow(self, df: DataFrame, d: int, blocks: list[int] | None = None, group: int = 0) -> DataFrame:
        """(block, bucket, v packed): buffers of all blocks inside each task, then sums.

        A task holds ``blocks * width * d`` doubles; ``group`` blocks at a time bound it."""
        use = list(range(self.blocks)) if blocks is None else list(blocks)
        if group and len(use) > group:
            halves = [self.apply_arrow(df, d, use[i : i + group]) for i in range(0, len(use), group)]
            out = halves[0]
            for h in halves[1:]:
                out = out.unionByName(h)
            return out
        me = self

        def run(batches):
            into = {k: np.zeros((me.width, d)) for k in use}
            for batch in batches:
                me.scatter(batch.column("row_id").to_numpy(), matrix(batch.column("x"), d), into, use)
            for k in use:
                live = np.flatnonzero(into[k].any(axis=1))
                yield pa.record_batch([pa.array(np.full(len(live), k, np.int32)), pa.array(live.astype(np.int32)), pa.array([pack(into[k][j]) for j in live], pa.binary())], names=["block", "bucket", "v"])

        return sum_packed(df.select("row_id", "x").mapInArrow(run, "block int, bucket int, v binary"), ["block", "bucket"])


# ------------------------------------------------------------------ Gram matrices
def gram_sql(sketched: DataFrame, used: int) -> DataFrame:
    """(i, j, h), i <= j: the sketched Gram matrix of (block, bucket, i, v)."""
    right = sketched.select("block", "bucket", F.col("i").alias("j"), F.col("v").alias("u"))
    return sketched.join(right, ["block", "bucket"]).where("i <= j").groupBy("i", "j").agg((F.sum(F.col("v") * F.col("u")) / used).alias("h"))


def gram_tiles(sketched: DataFrame, d: int, tile: int, need: int, arrivals: DataFrame | None = None) -> DataFrame:
    """(ci, cj, v packed): tiles ci <= cj of the Gram matrix of (block, bucket, v packed).

    Each tile adds the first ``need`` block products by arrival: ``arrivals`` has (block,
    ci, cj, t); without it all blocks count as arrived in order."""
    cuts = [(c, lo, min(d, lo + tile)) for c, lo in enumerate(range(0, d, tile))]

    def cut(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            v = np.frombuffer(b"".join(batch.column("v").to_pylist()), np.float64).reshape(batch.num_rows, d)
            parts = [np.ascontiguousarray(v[:, lo:hi]) for _, lo, hi in cuts]
            index = pa.array(np.tile(np.arange(batch.num_rows), len(cuts)))
            ci = pa.array(np.repeat(np.arange(len(cuts), dtype=np.int32), batch.num_rows))
            yield pa.record_batch([batch.column("block").take(index), batch.column("bucket").take(index), ci, pa.array([row.tobytes() for p in parts for row in p], pa.binary())], names=["block", "bucket", "ci", "v"])

    def product(table: pa.Table) -> pa.Table:
        stack = lambda c: np.stack([np.frombuffer(x, np.float64) for x in table.column(c).to_pylist()])
        return pa.table({**{k: table.column(k).slice(0, 1) for k in ("block", "ci", "cj")}, "v": pa.array([pack(stack("v").T @ stack("u"))], pa.binary())})

    from pyspark.sql import Window

    parts = sketched.select("block", "bucket", "v").mapInArrow(cut, "block int, bucket int, ci int, v binary")
    pairs = parts.join(parts.select("block", "bucket", F.col("ci").alias("cj"), F.col("v").alias("u")), ["block", "bucket"]).where("ci <= cj")
    tiles = pairs.select("block", "ci", "cj", "v", "u").groupBy("block", "ci", "cj").applyInArrow(product, "block int, ci int, cj int, v binary")
    order = ["block"]
    if arrivals is not None:
        tiles, order = tiles.join(arrivals, ["block", "ci", "cj"]), ["t", "block"]
    first = tiles.withColumn("r", F.row_number().over(Window.partitionBy("ci", "cj").orderBy(*order))).where(F.col("r") <= need)
    return sum_packed(first.select("ci", "cj", "v"), ["ci", "cj"])


def assemble(tiles: list, d: int, tile: int, used: int) -> np.ndarray:
    """The symmetric matrix of collected tiles, divided by the number of blocks used."""
    h = np.zeros((d, d))
    for r in tiles:
        a, b = r["ci"] * tile, r["cj"] * tile
        part = np.frombuffer(r["v"], np.float64).reshape(min(tile, d - a), -1)
        h[a : a + part.shape[0], b : b + part.shape[1]] = part
        h[b : b + part.shape[1], a : a + part.shape[0]] = part.T
    return h / used


def gram_driver(sketched: DataFrame, d: int, used: int) -> np.ndarray:
    """The Gram matrix at the driver; for sketches of a few hundred MB at most."""
    rows = [np.frombuffer(r["v"], np.float64) for r in sketched.select("v").toLocalIterator()]
    a = np.stack(rows) if rows else np.zeros((0, d))
    return a.T @ a / used


def gram_exact(df: DataFrame, d: int) -> np.ndarray:
    """A'A of root rows (x): one product for each batch, one partial for each task."""

    def run(batches):
        h = np.zeros((d, d))
        for batch in batches:
            a = matrix(batch.column("x"), d)
            h += a.T @ a
        yield pa.record_batch([pa.array([0], pa.int32()), pa.array([pack(h)], pa.binary())], names=["k", "v"])

    out = sum_packed(df.select("x").mapInArrow(run, "k int, v binary"), ["k"]).collect()
    return np.frombuffer(out[0]["v"], np.float64).reshape(d, d) if out else np.zeros((d, d))


def gram_long(df: DataFrame) -> DataFrame:
    """(i, j, h), i <= j: the exact Gram matrix in JVM operators, row by row."""
    long = df.select("x", F.posexplode("x").alias("i", "v")).select("i", "v", F.posexplode("x").alias("j", "u"))
    return long.where("i <= j").groupBy("i", "j").agg(F.sum(F.col("v") * F.col("u")).alias("h"))


# ------------------------------------------------------------------ other embeddings
def gaussian(df: DataFrame, d: int, m: int, seed: int = 0) -> DataFrame:
    """(block, bucket, v): m dense rows of hash-seeded normals, scaled to unit variance."""

    def run(batches):
        total = np.zeros((m, d))
        for batch in batches:
            ids = batch.column("row_id").to_numpy()
            x = matrix(batch.column("x"), d)
            for j in range(0, m, 64):
                k = min(64, m - j)
                u1 = np.stack([uniform_np(ids, seed + 31, 2 * (j + t)) for t in range(k)])
                u2 = np.stack([uniform_np(ids, seed + 31, 2 * (j + t) + 1) for t in range(k)])
                g = np.sqrt(-2 * np.log(np.maximum(u1, 1e-12))) * np.cos(2 * np.pi * u2)
                total[j : j + k] += g @ x / math.sqrt(m)
        yield pa.record_batch([pa.array(np.zeros(m, np.int32)), pa.array(np.arange(m, dtype=np.int32)), pa.array([pack(r) for r in total], pa.binary())], names=["block", "bucket", "v"])

    return sum_packed(df.select("row_id", "x").mapInArrow(run, "block int, bucket int, v binary"), ["block", "bucket"])


def sparse_jl(df: DataFrame, m: int, s: int, seed: int = 0) -> DataFrame:
    """(block, bucket, i, v): s signed copies of each row in m buckets, scaled 1/sqrt(s)."""
    out = BlockSketch(s, 0, max(1, m // s), seed).apply_sql(df)
    return out.withColumn("v", F.col("v") / math.sqrt(s))


def row_sample(df: DataFrame, q: float, seed: int = 0, leverage: bool = False, d: int = 0) -> DataFrame:
    """Rows kept with probability q (or in proportion to their squared length, at most 1),
    scaled by one over the root of that probability; a stand-in root matrix."""
    u = hash_col(F.col("row_id"), coefficients(seed + 53)) / 2147483647.0
    p = F.lit(float(q))
    if leverage:
        sq = F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v)
        mean = df.agg(F.avg(sq)).collect()[0][0] or 1.0
        p = F.least(F.lit(1.0), sq / mean * q)
    return df.withColumn("_p", p).where(u < F.col("_p")).withColumn("x", F.transform("x", lambda v: v / F.sqrt("_p"))).drop("_p")


def hadamard(df: DataFrame, d: int, rows: int, keep: int, seed: int = 0) -> DataFrame:
    """(block, bucket, v): signed rows in groups of ``rows`` (a power of two) turned by a
    Walsh-Hadamard matrix; ``keep`` of each group's rows, scaled."""
    if rows & (rows - 1):
        raise ValueError("rows must be a power of two")

    def turn(table: pa.Table) -> pa.Table:
        g = table.column("g")[0].as_py()
        ids = table.column("row_id").to_numpy()
        x = matrix(table.column("x"), d)
        h = hash_np(ids, coefficients(seed + 61))
        full = np.zeros((rows * -(-len(ids) // rows), d))
        full[: len(ids)] = (x * (1.0 - 2.0 * (h % 2))[:, None])[np.argsort(ids)]
        out = []
        for lo in range(0, len(full), rows):
            part, step = full[lo : lo + rows].copy(), 1
            while step < rows:
                for i in range(0, rows, 2 * step):
                    a, b = part[i : i + step].copy(), part[i + step : i + 2 * step].copy()
                    part[i : i + step], part[i + step : i + 2 * step] = a + b, a - b
                step *= 2
            pick = np.argsort(hash_np(np.arange(rows) + lo + 1 + rows * g, coefficients(seed + 67)))[:keep]
            out += list(part[pick] / math.sqrt(keep))
        return pa.table({"block": pa.array(np.full(len(out), g, np.int32)), "bucket": pa.array(np.arange(len(out), dtype=np.int32)), "v": pa.array([pack(r) for r in out], pa.binary())})

    n = df.count()
    groups = max(1, n // (4 * rows))
    return df.select("row_id", "x", F.pmod(F.xxhash64("row_id"), F.lit(groups)).cast("int").alias("g")).groupBy("g").applyInArrow(turn, "block int, bucket int, v binary")
