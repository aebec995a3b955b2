"""Arrival times of workers, straggler policies, and simulated cost.

Simulated seconds come from hash draws of (trial, phase, worker, attempt); they are a model
and never measured time."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import coefficients, hash_col, hash_np
from ..operators.coding import wait_set


@dataclass(frozen=True)
class ArrivalModel:
    """Most workers need about ``base`` seconds; a share ``tail`` of them up to ``slow``."""

    base: float = 135.0
    spread: float = 0.02
    tail: float = 0.02
    slow: float = 180.0
    seed: int = 11

    def _t(self, u, v, where):
        quick = self.base * (1 + self.spread * (2 * v - 1))
        return where(u < self.tail, self.base * 1.1 + (self.slow - self.base * 1.1) * v, quick)

    def draw(self, n: int, trial: int = 0, phase: int = 0, attempt: int = 0) -> np.ndarray:
        ids = ((np.arange(n, dtype=np.int64) * 16 + phase) * 8 + attempt) * 4096 + trial
        u = hash_np(ids, coefficients(self.seed, 0)) / 2147483647.0
        v = hash_np(ids, coefficients(self.seed, 1)) / 2147483647.0
        return self._t(u, v, np.where)

    def table(self, spark: SparkSession, n: int, trials: int, phase: int = 0) -> DataFrame:
        """(trial, worker, t, t2): first and relaunched attempts."""
        return self.times(spark.range(n * trials), trials, phase)

    def times(self, ids: DataFrame, trials: int, phase: int = 0) -> DataFrame:
        """Likewise for the ids of a table: dealt to trials in turn."""
        ids = ids.toDF("id").select((F.col("id") % trials).cast("int").alias("trial"), F.expr(f"id div {trials}").alias("worker"))

        def at(attempt):
            key = ((F.col("worker") * 16 + phase) * 8 + attempt) * 4096 + F.col("trial")
            u, v = (hash_col(key, coefficients(self.seed, k)) / 2147483647.0 for k in (0, 1))
            return self._t(u, v, lambda c, a, b: F.when(c, a).otherwise(b))

        return ids.select("trial", "worker", at(0).alias("t"), at(1).alias("t2"))


def order_statistics(times: DataFrame, ranks: dict) -> DataFrame:
    """(trial, a column for each name): the exact times at 1-based ranks in each trial of
    (trial, t).  ``ranks`` has functions of the number of times.  Bins of a thousandth of a
    second are counted, and only the bins that hold a rank are sorted."""
    rows = times.select("trial", "t", F.floor(F.col("t") * 1000).alias("_bin"))
    upto = F.sum("_c").over(Window.partitionBy("trial").orderBy("_bin"))
    n = F.sum("_c").over(Window.partitionBy("trial"))
    bins = rows.groupBy("trial", "_bin").agg(F.count(F.lit(1)).alias("_c")).select("trial", "_bin", (upto - F.col("_c")).alias("_before"), upto.alias("_upto"), n.alias("_n"))
    wanted = F.array(*[F.struct(F.lit(k).alias("name"), f(F.col("_n")).cast("long").alias("rank")) for k, f in ranks.items()])
    bins = bins.select("trial", "_bin", "_before", "_upto", F.explode(wanted).alias("_w")).where("_w.rank > _before AND _w.rank <= _upto")
    place = F.row_number().over(Window.partitionBy("trial", "_bin", "_w.name").orderBy("t"))
    hit = rows.join(F.broadcast(bins), ["trial", "_bin"]).withColumn("_r", place).where("_r = _w.rank - _before")
    return hit.groupBy("trial").agg(*[F.max(F.when(F.col("_w.name") == k, F.col("t"))).alias(k) for k in ranks])


def quantile(t: np.ndarray, q: float) -> float:
    return float(np.sort(t)[max(0, math.ceil(q * len(t)) - 1)])


class WaitAll:
    name = "wait"

    def finish(self, t, t2, work: float = 1.0) -> float:
        return float(t.max()) * work


@dataclass(frozen=True)
class Speculative:
    """After a share q is done, the rest are started again; the earlier copy counts."""

    q: float = 0.9
    name = "speculative"

    def finish(self, t, t2, work=1.0):
        c = quantile(t, self.q)
        return float(np.minimum(t, c + t2)[t > c].max(initial=c)) * work


@dataclass(frozen=True)
class IgnoreStragglers:
    keep: float = 0.95
    name = "ignore"

    def finish(self, t, t2, work=1.0):
        return quantile(t, self.keep) * work

    def survivors(self, t) -> np.ndarray:
        return t <= quantile(t, self.keep)


@dataclass(frozen=True)
class CodedGrid:
    """The first arrivals from which the product code can be peeled."""

    name = "coded"

    def finish(self, t, t2, work=1.0):
        g = max(1, int(math.sqrt(len(t))) - 1)
        cells = [(i // (g + 1), i % (g + 1)) for i in range((g + 1) ** 2)]
        use = t[: len(cells)]
        order = [cells[i] for i in np.argsort(use, kind="stable")]
        return float(np.sort(use)[wait_set(order, g) - 1]) * work


@dataclass(frozen=True)
class AnyN:
    """Any N of N + e blocks of every tile; ``tiles`` tiles wait each for themselves."""

    n: int
    spare: int
    name = "any-n"

    def finish(self, t, t2, work=1.0):
        per = self.n + self.spare
        if len(t) < per:  # several blocks for a worker: the same share of workers suffices
            return quantile(t, self.n / per) * work
        tiles = max(1, len(t) // per)
        return float(np.sort(t[: tiles * per].reshape(tiles, per), axis=1)[:, self.n - 1].max()) * work


@dataclass(frozen=True)
class GradientCode:
    s: int = 1
    name = "gradient-code"

    def finish(self, t, t2, work=1.0):
        return float(np.sort(t)[len(t) - self.s - 1]) * work * (self.s + 1)


@dataclass(frozen=True)
class Replicate:
    copies: int = 2
    name = "replicate"

    def finish(self, t, t2, work=1.0):
        return float(np.minimum(t, t2).max()) * work


@dataclass(frozen=True)
class ClusterProfile:
    """Seconds of a round besides the work: start, and exchange by bytes."""

    start: float
    per_gb: float
    model: ArrivalModel
    unit: float = 1.0  # scales a worker's time
    workers: int = 60

    def round(self, policy, n: int, trial: int, phase: int, nbytes: float = 0.0, work: float = 1.0) -> float:
        t, t2 = self.model.draw(n, trial, phase, 0), self.model.draw(n, trial, phase, 1)
        return self.start + self.per_gb * nbytes / 1e9 + self.unit * policy.finish(t, t2, work)


FUNCTIONS = ClusterProfile(2.0, 8.0, ArrivalModel(base=1.0, slow=1.0 * 180 / 135), 1.0)
SERVERS = ClusterProfile(0.05, 1.0, ArrivalModel(base=1.0, slow=1.02, tail=0.0), 0.75)


# ------------------------------------------------------------------ cost counts
def workers(scheme: str, blocks: int = 0, d: int = 0, b: int = 1, n: int = 0, spare: int = 0) -> int:
    """Workers of a phase: a coded mat-vec of ``blocks`` row blocks, a sketched or an exact
    Gram matrix of d x d in tiles of b, or its reduction."""
    tiles = math.ceil(d / b) ** 2
    if scheme == "matvec":
        root = math.ceil(math.sqrt(blocks))
        return root * root + 2 * root + 1
    if scheme == "sketched":
        return (n + spare) * tiles
    if scheme == "exact":
        return n * tiles
    return tiles


def comm_bytes(scheme: str, rows: int, d: int, n: int = 0, b: int = 0, spare: int = 0, tasks: int = 1) -> int:
    """Bytes that a round exchanges."""
    if scheme == "gradient":
        return 8 * d * tasks
    if scheme == "exact":
        return 8 * d * (d + 1) // 2 * tasks
    if scheme == "sketched":
        return 8 * (n + spare) * b * d * min(tasks, max(1, rows // max(1, b)))
    if scheme == "encode":
        return 2 * 8 * rows * d
    raise ValueError(scheme)


def choose_hessian(rows: int, d: int, n: int, spare: int, b: int, tasks: int, flops: float = 1e10, bandwidth: float = 1e9) -> str:
    """'exact' or 'sketched', by modelled seconds of CPU and exchange."""
    exact = rows * d * d / 2 / flops + comm_bytes("exact", rows, d, tasks=tasks) / bandwidth
    sketch = rows * d * (n + spare) / flops + comm_bytes("sketched", rows, d, n, b, spare, tasks) / bandwidth
    return "exact" if exact <= sketch else "sketched"


def matmul_bytes(scheme: str, n: int, d: int, b: int) -> int:
    """Bytes that workers read for A'A of n x d in all, each holding 2 b^2 entries: square
    blocks of b, or strips of whole columns, of which only b^2 / n fit."""
    if scheme == "block":
        return 8 * 2 * b * b * math.ceil(n / b) * math.ceil(d / b) ** 2
    strip = max(1, b * b // n)
    return 8 * 2 * n * strip * math.ceil(d / strip) ** 2
