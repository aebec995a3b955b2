"""Coded redundancy: product-coded mat-vecs with peeling, single parity, gradient codes,
and codes of which any k of n parts suffice."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import columns as X


# ------------------------------------------------------------------ product code
@dataclass
class ProductCode:
    """Row blocks on a g x g grid with a parity block for each line, row and column, and a
    corner.  ``blocks``: (r, c, offset, row_id, x); parities have row or column g."""

    blocks: DataFrame
    g: int
    size: int

    @staticmethod
    def encode(ranked: DataFrame, n_rows: int, grid: int) -> ProductCode:
        """From (rank, row_id, x): rank 0 .. n_rows - 1.  Missing rows of the last blocks
        count as zeros."""
        size = max(1, math.ceil(n_rows / (grid * grid)))
        data = ranked.select(
            F.floor(F.col("rank") / (size * grid)).cast("int").alias("r"),
            (F.floor(F.col("rank") / size) % grid).cast("int").alias("c"),
            (F.col("rank") % size).cast("int").alias("offset"),
            "row_id",
            "x",
        )
        return ProductCode(data.unionByName(ProductCode.parities(data, grid)), grid, size)

    @staticmethod
    def parities(data: DataFrame, g: int) -> DataFrame:
        """Row and column parities, a group of at most g vectors each; the corner from the
        row parities."""
        line = F.explode(F.array(F.struct(F.col("r").alias("pr"), F.lit(g).alias("pc")), F.struct(F.lit(g).alias("pr"), F.col("c").alias("pc"))))
        sums = data.select(line.alias("_p"), "offset", "x").groupBy("_p.pr", "_p.pc", "offset").agg(_array_sum("x").alias("x"))
        corner = sums.where(F.col("pc") == g).groupBy("offset").agg(_array_sum("x").alias("x")).select(F.lit(g).alias("pr"), F.lit(g).alias("pc"), "offset", "x")
        every = sums.unionByName(corner)
        return every.select(F.col("pr").alias("r"), F.col("pc").alias("c"), "offset", F.lit(None).cast("long").alias("row_id"), "x")

    def products(self, x) -> DataFrame:
        """(r, c, offset, row_id, y): every block times the vector."""
        return self.blocks.select("r", "c", "offset", "row_id", X.dot(F.col("x"), X.weights(x)).alias("y"))

    def decode(self, products: DataFrame, erased: set[tuple[int, int]]) -> DataFrame:
        """(row_id, y) of the data blocks from the products that arrived, in one pass: each
        lost data block is a signed sum of blocks that arrived."""
        plan = combinations(erased, self.g)
        spark = products.sparkSession
        data = products.where((F.col("r") < self.g) & (F.col("c") < self.g) & F.col("row_id").isNotNull())
        gone = [(r, c) for r, c in erased]
        lost = spark.createDataFrame(gone or [(-1, -1)], "r int, c int")
        here = data.join(F.broadcast(lost), ["r", "c"], "left_anti").select("row_id", "y")
        terms = [(r, c, tr, tc, float(v)) for (tr, tc), of in plan.items() if tr < self.g and tc < self.g for (r, c), v in of.items()]
        if not terms:
            return here
        table = spark.createDataFrame(terms, "r int, c int, tr int, tc int, coef double")
        found = products.join(F.broadcast(table), ["r", "c"]).groupBy("tr", "tc", "offset").agg(F.sum(F.col("coef") * F.col("y")).alias("y"))
        ids = self.blocks.where("row_id IS NOT NULL").select("r", "c", "offset", "row_id").join(F.broadcast(lost), ["r", "c"], "left_semi")
        return here.unionByName(ids.join(found.withColumnsRenamed({"tr": "r", "tc": "c"}), ["r", "c", "offset"]).select("row_id", "y"))


def _array_sum(column: str):
    """The sum of a group's arrays, entry by entry; for groups of bounded size."""
    every = F.collect_list(column)
    return F.aggregate(F.slice(every, 2, F.greatest(F.size(every) - 1, F.lit(0))), F.get(every, 0), lambda a, x: F.zip_with(a, x, lambda u, v: u + v))


def placed(df: DataFrame, g: int, per: int = 50_000) -> tuple[DataFrame, int]:
    """Adds (r, c, offset) to rows with a ``row_id``: blocks dealt by hash, and in each the
    place within one of its parts of about ``per`` rows.  No window holds more than a part."""
    n = df.count()
    parts = max(1, math.ceil(n / (g * g * per)))
    block = F.pmod(F.xxhash64("row_id", F.lit("block")), F.lit(g * g))
    rows = df.withColumns({"_block": block, "_part": F.pmod(F.xxhash64("row_id", F.lit("part")), F.lit(parts))})
    rows = rows.withColumn("_at", F.row_number().over(Window.partitionBy("_block", "_part").orderBy("row_id")) - 1)
    stride = (rows.agg(F.max("_at")).collect()[0][0] or 0) + 1
    out = rows.withColumns({"r": F.floor(F.col("_block") / g).cast("int"), "c": (F.col("_block") % g).cast("int"), "offset": F.col("_part") * stride + F.col("_at")})
    return out.drop("_block", "_part", "_at"), parts * stride


def ranked(df: DataFrame, key: str) -> DataFrame:
    """Adds ``rank``, 0 .. n - 1 in the order of ``key``: ranges of keys, the sizes of the
    ranges before, and the place within a range."""
    rows = df.repartitionByRange(key).withColumn("_range", F.spark_partition_id()).persist()
    sizes = rows.groupBy("_range").count()
    before = sizes.select("_range", F.coalesce(F.sum("count").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_base"))
    place = F.row_number().over(Window.partitionBy("_range").orderBy(key)) - 1
    return rows.join(F.broadcast(before), "_range").withColumn("rank", place + F.col("_base")).drop("_range", "_base")


def combinations(erased: set[tuple[int, int]], g: int) -> dict[tuple[int, int], dict[tuple[int, int], float]]:
    """Each erased block as a signed sum of blocks that arrived, along the peeling order.

    A line's parity is the sum of its data blocks, and lines of parities sum to the corner
    likewise; so all blocks of a line but one give that one."""
    plan = peel(erased, g)
    if plan is None:
        raise ValueError("these blocks can't be decoded")
    known: dict[tuple[int, int], dict[tuple[int, int], float]] = {}
    for (r, c), line in plan:
        cells = [(r, k) for k in range(g + 1) if k != c] if line == "row" else [(k, c) for k in range(g + 1) if k != r]
        end = c if line == "row" else r
        total: dict[tuple[int, int], float] = {}
        for cell in cells:
            at = cell[1] if line == "row" else cell[0]
            sign = 1.0 if end == g or at == g else -1.0
            for source, v in known.get(cell, {cell: 1.0}).items():
                total[source] = total.get(source, 0.0) + sign * v
        known[r, c] = {k: v for k, v in total.items() if v}
    return known


def arrived(times: np.ndarray, g: int) -> tuple[set[tuple[int, int]], float]:
    """Of (g + 1)^2 blocks the ones that needn't be waited for, and when the others are
    there: blocks are awaited, in the order of their times, until the rest can be peeled."""
    cells = [(i // (g + 1), i % (g + 1)) for i in range((g + 1) ** 2)]
    order = np.argsort(times[: len(cells)], kind="stable")
    k = wait_set([cells[i] for i in order], g)
    return {cells[i] for i in order[k:]}, float(times[order[k - 1]])


def peel(erased: set[tuple[int, int]], g: int) -> list | None:
    """The order in which lines with one missing block give it back; None if stuck."""
    left, plan = set(erased), []
    while left:
        for cell in sorted(left):
            if sum(1 for o in left if o[0] == cell[0]) == 1:
                plan.append((cell, "row"))
            elif sum(1 for o in left if o[1] == cell[1]) == 1:
                plan.append((cell, "col"))
            else:
                continue
            left.remove(cell)
            break
        else:
            return None
    return plan


def wait_set(order: list[tuple[int, int]], g: int) -> int:
    """How many arrivals, in order, are needed until the rest can be peeled."""
    every = {(r, c) for r in range(g + 1) for c in range(g + 1)}
    lo, hi = 1, len(order)
    while lo < hi:
        mid = (lo + hi) // 2
        if peel(every - set(order[:mid]), g) is None:
            lo = mid + 1
        else:
            hi = mid
    return lo


def decode_rate(g: int, p: float, trials: int = 2000, seed: int = 0) -> float:
    """Share of random erasures (each block with probability p) that can be peeled."""
    rng = np.random.default_rng(seed)
    good = 0
    for _ in range(trials):
        hit = np.argwhere(rng.random((g + 1, g + 1)) < p)
        good += peel({tuple(x) for x in hit.tolist()}, g) is not None
    return good / trials


# ------------------------------------------------------------------ gradient codes
def cyclic_code(workers: int, s: int, seed: int = 1) -> np.ndarray:
    """(workers, parts): each worker holds s + 1 cyclic parts; any workers - s rows span
    the all-ones vector.  The rows are drawn in the null space of a random matrix whose
    rows sum to zero."""
    if not 0 <= s < workers:
        raise ValueError("0 <= s < workers is needed")
    if s == 0:
        return np.eye(workers)
    rng = np.random.default_rng(seed)
    h = rng.normal(size=(s, workers))
    h[:, -1] = -h[:, :-1].sum(axis=1)
    b = np.zeros((workers, workers))
    for i in range(workers):
        cols = [(i + j) % workers for j in range(s + 1)]
        b[i, cols[0]] = 1.0
        b[i, cols[1:]] = np.linalg.solve(h[:, cols[1:]], -h[:, cols[0]])
    return b


def fractional_code(workers: int, s: int) -> np.ndarray:
    """Groups of s + 1 workers that all hold the same s + 1 parts."""
    if workers % (s + 1):
        raise ValueError("s + 1 must divide the number of workers")
    b = np.zeros((workers, workers))
    for i in range(workers):
        a = i // (s + 1) * (s + 1)
        b[i, a : a + s + 1] = 1.0
    return b


def decode_vector(code: np.ndarray, survivors: list[int]) -> np.ndarray:
    """Weights of the survivors' messages that give the full sum."""
    a, *_ = np.linalg.lstsq(code[survivors].T, np.ones(code.shape[1]), rcond=None)
    if np.abs(code[survivors].T @ a - 1).max() > 1e-6:
        raise ValueError("too few survivors")
    return a


def placement(spark, code: np.ndarray) -> DataFrame:
    rows = [(int(w), int(p), float(code[w, p])) for w, p in np.argwhere(code != 0)]
    return spark.createDataFrame(rows, "worker int, shard int, coef double")


def coded_sum(partials: DataFrame, code: np.ndarray, survivors: list[int]) -> DataFrame:
    """(i, g): the full sum from the survivors' coded messages of (shard, i, g)."""
    a = decode_vector(code, survivors)
    spark = partials.sparkSession
    weight = spark.createDataFrame([(w, float(v)) for w, v in zip(survivors, a)], "worker int, weight double")
    sent = partials.join(F.broadcast(placement(spark, code)), "shard").groupBy("worker", "i").agg(F.sum(F.col("coef") * F.col("g")).alias("m"))
    return sent.join(F.broadcast(weight), "worker").groupBy("i").agg(F.sum(F.col("weight") * F.col("m")).alias("g"))


# ------------------------------------------------------------------ any k of n
def mds_code(k: int, r: int) -> np.ndarray:
    """(k + r, k): identity above rows of powers; any k rows are independent."""
    points = np.cos(np.pi * (2 * np.arange(k + r) + 1) / (2 * (k + r)))
    v = np.vander(points, k, increasing=True)
    return v @ np.linalg.inv(v[:k])


def mds_encode(data: DataFrame, k: int, r: int) -> DataFrame:
    """(part, offset, i, v) of the k + r coded parts from parts 0 .. k - 1 of the same."""
    spark, g = data.sparkSession, mds_code(k, r)
    table = spark.createDataFrame([(int(a), int(b), float(g[a, b])) for a in range(k + r) for b in range(k)], "code int, part int, c double")
    return data.join(F.broadcast(table), "part").groupBy("code", "offset", "i").agg(F.sum(F.col("c") * F.col("v")).alias("v")).withColumnRenamed("code", "part")


def mds_decode(results: DataFrame, k: int, r: int, survivors: list[int]) -> DataFrame:
    """(part, offset, y) of the data parts from k surviving parts' (part, offset, y)."""
    inv = np.linalg.inv(mds_code(k, r)[survivors[:k]])
    spark = results.sparkSession
    table = spark.createDataFrame([(int(p), int(s), float(inv[p, j])) for p in range(k) for j, s in enumerate(survivors[:k])], "data int, part int, c double")
    return results.join(F.broadcast(table), "part").groupBy("data", "offset").agg(F.sum(F.col("c") * F.col("y")).alias("y")).withColumnRenamed("data", "part")
