"""The gradient by two coded mat-vecs, from data that is encoded once for all iterations.

``CodedPair`` keeps both orientations of a design matrix under a product code: row blocks on
a grid, for the products x.w of all rows; and feature blocks on a grid, for the sum of the
rows weighed by the slopes.  In each round the blocks are awaited, by their arrival times,
until the rest can be peeled; products of the rest aren't used.  The products of the rows are
decoded in one distributed pass; the second round's blocks are vectors of the model's size,
decoded at the driver.  The sketch of the Hessian's root rides on the second round.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.coding import ProductCode, arrived, combinations, cyclic_code, decode_vector, placed
from ..operators.sketch import BlockSketch
from ..operators.vectors import matrix, pack, sum_packed
from ..sources.design import DesignMatrix
from .arrivals import ArrivalModel


@dataclass
class Round:
    """What a coded evaluation gives, and how long its two rounds had to wait."""

    n: float
    loss: float
    gradient: np.ndarray
    rows: np.ndarray | None
    block_of: np.ndarray | None
    erased: tuple[set, set]
    waited: tuple[float, float]


def feature_blocks(x: np.ndarray, g: int) -> np.ndarray:
    """(rows, (g + 1)^2, size): the feature blocks of each row on a g x g grid, zeros behind
    the last feature, with the parities of the grid's rows and columns and its corner."""
    n, d = x.shape
    size = -(-d // (g * g))
    out = np.zeros((n, g + 1, g + 1, size))
    flat = np.zeros((n, g * g * size))
    flat[:, :d] = x
    out[:, :g, :g] = flat.reshape(n, g, g, size)
    out[:, g, :g] = out[:, :g, :g].sum(axis=1)
    out[:, :, g] = out[:, :, :g].sum(axis=2)
    return out.reshape(n, (g + 1) ** 2, size)


def joined_blocks(blocks: np.ndarray, erased: set, g: int, d: int) -> np.ndarray:
    """The d entries of a vector from its coded blocks ((g + 1)^2, size) without the erased."""
    grid = blocks.reshape(g + 1, g + 1, -1).copy()
    for cell in erased:
        grid[cell] = np.nan
    for cell, of in combinations(erased, g).items():
        grid[cell] = sum(v * grid[source] for source, v in of.items())
    return grid[:g, :g].reshape(-1)[:d]


def save_blocks(blocks: DataFrame, path: str) -> None:
    """Coded blocks (r, c, ...) in a folder for each, so that lost ones aren't read."""
    blocks.write.mode("overwrite").partitionBy("r", "c").parquet(path)


class CodedPair:
    def __init__(self, rows: ProductCode, columns: DataFrame, g: int, g_features: int, d: int):
        self.rows, self.columns, self.g, self.gf, self.d = rows, columns, g, g_features, d

    @staticmethod
    def encode(data: DesignMatrix, g: int = 3, g_features: int | None = None, path: str | None = None) -> CodedPair:
        """Encode once.  Both tables are persisted, or written under ``path`` (a folder that
        all machines share) and read from there."""
        spark, d = data.df.sparkSession, data.d
        gf = g_features or max(1, min(3, math.isqrt(d)))
        at, size = placed(data.df.select("row_id", F.col("y").cast("double").alias("y"), "x"), g)
        plain = at.select("r", "c", "offset", "row_id", "x")
        code = plain.unionByName(ProductCode.parities(plain, g))
        length = (gf + 1) ** 2 * -(-d // (gf * gf))

        def cut(batches):
            for batch in batches:
                b = feature_blocks(matrix(batch.column("x"), d), gf).reshape(-1)
                xs = pa.ListArray.from_arrays(pa.array(np.arange(batch.num_rows + 1) * length, pa.int32()), pa.array(b))
                yield pa.record_batch([batch.column("row_id"), batch.column("y"), xs], names=["row_id", "y", "blocks"])

        columns = at.select("row_id", "y", "x").mapInArrow(cut, "row_id long, y double, blocks array<double>")
        columns = columns.repartition("row_id")
        if path:
            save_blocks(code, f"{path}/rows")
            columns.write.mode("overwrite").parquet(f"{path}/columns")
            code, columns = spark.read.parquet(f"{path}/rows"), spark.read.parquet(f"{path}/columns")
        else:
            code, columns = code.persist(), columns.persist()
        return CodedPair(ProductCode(code, g, size), columns, g, gf, d)

    def release(self) -> None:
        self.rows.blocks.unpersist()
        self.columns.unpersist()

    def products(self, w, erased: set) -> DataFrame:
        """(row_id, y): x.w of every row, those of the erased blocks from the others."""
        blocks = self.rows.blocks
        for r, c in sorted(erased):  # literal filters: folders of written blocks are pruned
            blocks = blocks.where((F.col("r") != r) | (F.col("c") != c))
        live = ProductCode(blocks, self.g, self.rows.size).products(w)
        return self.rows.decode(live, erased)

    def evaluate(self, problem, w, it: int = 0, model: ArrivalModel | None = None, sketch: BlockSketch | None = None, blocks=None, fan: int = 0) -> Round:
        """Loss and gradient at w by the two coded rounds, and the sketched Hessian root."""
        model, d, gf = model or ArrivalModel(), self.d, self.gf
        first, t1 = arrived(model.draw((self.g + 1) ** 2, it, 0), self.g)
        second, t2 = arrived(model.draw((gf + 1) ** 2, it, 1), gf)
        use = list(range(sketch.blocks)) if sketch is not None and blocks is None else list(blocks or [])
        cells, size = (gf + 1) ** 2, -(-d // (gf * gf))

        def run(batches):
            n, loss, total = 0, 0.0, np.zeros((cells, size))
            into = {k: np.zeros((sketch.width, d)) for k in use} if sketch is not None else {}
            for batch in batches:
                b = matrix(batch.column("blocks"), cells * size)
                value, slope, bend = problem.at_margins(batch.column("t").to_numpy(), batch.column("y").to_numpy())
                n, loss = n + len(b), loss + float(value.sum())
                total += (slope @ b).reshape(cells, size)
                if into:
                    x = b.reshape(-1, gf + 1, gf + 1, size)[:, :gf, :gf].reshape(len(b), -1)[:, :d]
                    sketch.scatter(batch.column("row_id").to_numpy(), np.sqrt(bend)[:, None] * x, into, use)
            out = [(-1, 0, np.array([n, loss]))] + [(-2, i, v) for i, v in enumerate(total)]
            if into:
                out += list(sketch.slabs(into))
            yield pa.record_batch([pa.array([o[0] for o in out], pa.int32()), pa.array([o[1] for o in out], pa.int32()), pa.array([pack(o[2]) for o in out], pa.binary())], names=["block", "bucket", "v"])

        met = self.columns.join(self.products(w, first).withColumnRenamed("y", "t"), "row_id")
        parts = met.select("row_id", "y", "blocks", "t").mapInArrow(run, "block int, bucket int, v binary")
        n, loss, coded, rows, of = 0.0, 0.0, np.zeros((cells, size)), [], []
        for r in sum_packed(parts, ["block", "bucket"], fan=fan).collect():
            v = np.frombuffer(r["v"], np.float64)
            if r["block"] == -1:
                n, loss = v
            elif r["block"] == -2:
                coded[r["bucket"]] = v
            else:
                rows.append(v.reshape(-1, d))
                of.append(np.full(len(rows[-1]), r["block"]))
        scale = 1.0 / max(n, 1) if problem.mean else 1.0
        g = joined_blocks(coded, second, gf, d) * scale + problem.reg_gradient(w)
        found = (np.concatenate([np.zeros((0, d)), *rows]), np.concatenate([np.zeros(0, int), *of])) if sketch is not None else (None, None)
        return Round(n, loss * scale + problem.reg_loss(w), g, *found, (first, second), (t1, t2))


# ------------------------------------------------------------------ gradient codes
def shard_gradients(data: DesignMatrix, problem, w, shards: int, shard) -> tuple[np.ndarray, float]:
    """(shards, width) gradient sums of the hash shards, and the number of rows."""
    d, size = data.d, problem.width(data.d)

    def run(batches):
        total, n = {}, 0
        for batch in batches:
            x, y, of = matrix(batch.column("x"), d), batch.column("y").to_numpy(), batch.column("shard").to_numpy()
            n += len(y)
            for k in np.unique(of).tolist():
                at = of == k
                total[k] = total.get(k, 0.0) + problem.gradient(x[at], y[at], w)
        out = [(-1, np.array([float(n)])), *total.items()]
        yield pa.record_batch([pa.array([k for k, _ in out], pa.int32()), pa.array([pack(v) for _, v in out], pa.binary())], names=["shard", "v"])

    parts = data.df.select(shard.cast("int").alias("shard"), F.col("y").cast("double").alias("y"), "x").mapInArrow(run, "shard int, v binary")
    out, n = np.zeros((shards, size)), 0.0
    for r in sum_packed(parts, ["shard"]).collect():
        if r["shard"] < 0:
            n = float(np.frombuffer(r["v"], np.float64)[0])
        else:
            out[r["shard"]] = np.frombuffer(r["v"], np.float64)
    return out, n


GROUP = 60  # workers that share a code; each group bears s slow ones


def coded_gradient(data: DesignMatrix, problem, w, workers: int, s: int, shard, times: np.ndarray) -> np.ndarray:
    """The full gradient from the messages of all workers but the s slowest of each group:
    each sends a fixed combination of the gradients of its s + 1 shards."""
    parts, n = shard_gradients(data, problem, w, workers, shard)
    return decoded(parts, n, problem, w, s, times)


def decoded(parts: np.ndarray, n: float, problem, w, s: int, times: np.ndarray) -> np.ndarray:
    """The gradient of n rows from the workers' gradients, by codes of about ``GROUP`` workers."""
    workers, codes = len(parts), {}
    total = np.zeros(parts.shape[1])
    for group in np.array_split(np.arange(workers), max(1, workers // GROUP)):
        code = codes[len(group)] if len(group) in codes else codes.setdefault(len(group), cyclic_code(len(group), s))
        live = sorted(np.argsort(times[group], kind="stable")[: len(group) - s].tolist())
        messages = code[live] @ parts[group]
        total += decode_vector(code, live) @ messages
    return total * (1.0 / max(n, 1) if problem.mean else 1.0) + problem.reg_gradient(w)
