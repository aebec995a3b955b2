"""Arrival times, straggler policies, costs, and measures on a fixed trace."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import columns as X
from ..functions.hashing import coefficients, hash_sql, hash_sql_long
from ..plans import arrivals, measures
from ..plans.optimise import GRID
from ..sources import design, tables
from .base import W_SQL, Registry, emb, margin, rounded, w_fix

QUERIES = Registry()
q = QUERIES.add
MODEL = arrivals.ArrivalModel()
N, TRIALS = 3600, 10


def _draw(attempt, hashed=hash_sql):
    key = f"((worker * 16 * 8 + {attempt}) * 4096 + trial)"
    u, v = (f"({hashed(key, coefficients(11, k))} / 2147483647.0)" for k in (0, 1))
    return f"CASE WHEN {u} < 0.02 THEN 135.0 * 1.1 + (180.0 - 135.0 * 1.1) * {v} ELSE 135.0 * (1 + 0.02 * (2 * {v} - 1)) END"


_T = f"WITH w AS (SELECT id % {TRIALS} AS trial, id // {TRIALS} AS worker FROM range(0, {N * TRIALS}) r(id)), t AS (SELECT trial, worker, ({_draw(0)})::DOUBLE AS t, ({_draw(1)})::DOUBLE AS t2 FROM w)"
_QS = f"{_T}, o AS (SELECT *, row_number() OVER (PARTITION BY trial ORDER BY t, worker) AS r FROM t)"


def _times(spark):
    return MODEL.table(spark, N, TRIALS)


def _ranked(spark):
    return _times(spark).withColumn("r", F.row_number().over(Window.partitionBy("trial").orderBy("t", "worker")))


#: A worker for each order, dealt to ten trials; keys pass the prime, so both limbs are hashed.
_TO = f"WITH w AS (SELECT o_orderkey % {TRIALS} AS trial, o_orderkey // {TRIALS} AS worker FROM orders), t AS (SELECT trial, worker, ({_draw(0, hash_sql_long)})::DOUBLE AS t, ({_draw(1, hash_sql_long)})::DOUBLE AS t2 FROM w)"
_QO = f"{_TO}, o AS (SELECT *, row_number() OVER (PARTITION BY trial ORDER BY t, worker) AS r, count(*) OVER (PARTITION BY trial) AS n FROM t)"


def _order_times(spark, sf):
    return MODEL.times(tables.table(spark, sf, "orders", "o_orderkey"), TRIALS)


@q(f"{_TO} SELECT trial, worker, round(t, 6) + 0.0 AS t, round(t2, 6) + 0.0 AS t2 FROM t WHERE worker < 200")
def arrival_table(spark, sf):
    """The first 200 workers of each trial; ``arrival_table_whole`` has all."""
    return rounded(_order_times(spark, sf).where("worker < 200"), "t", "t2")


@q(QUERIES["arrival_table"][1].replace(" WHERE worker < 200", ""))
def arrival_table_whole(spark, sf):
    return rounded(_order_times(spark, sf), "t", "t2")


@q(f"{_TO} SELECT round(quantile_cont(t, 0.5), 6) + 0.0 AS median, round(avg((t > 145)::INT), 6) + 0.0 AS slow, round(max(t), 6) + 0.0 AS longest, round(avg(CASE WHEN t > 145 THEN t END), 6) + 0.0 AS tail FROM t")
def arrival_summary(spark, sf):
    """Median, share of slow workers, and their mean: the job-time distribution."""
    rows, slow = _order_times(spark, sf), F.col("t") > 145
    middle = arrivals.order_statistics(rows.select(F.lit(0).alias("trial"), "t"), {"low": lambda n: F.floor((n + 1) / 2), "high": lambda n: F.floor(n / 2) + 1})
    out = rows.agg(F.avg(slow.cast("int")).alias("slow"), F.max("t").alias("longest"), F.avg(F.when(slow, F.col("t"))).alias("tail"))
    out = out.join(F.broadcast(middle.select(((F.col("low") + F.col("high")) / 2).alias("median"))), F.lit(True), "left")
    return rounded(out.select("median", "slow", "longest", "tail"), "median", "slow", "longest", "tail")


@q(f"{_QO} SELECT trial, round(max(CASE WHEN r = greatest(1, n // 2) THEN t END), 6) + 0.0 AS p50, round(max(CASE WHEN r = greatest(1, n * 9 // 10) THEN t END), 6) + 0.0 AS p90, round(max(CASE WHEN r = greatest(1, n * 49 // 50) THEN t END), 6) + 0.0 AS p98 FROM o GROUP BY trial")
def arrival_ranks(spark, sf):
    """The times when a half, nine tenths and 98 % of a trial's workers are done."""
    at = lambda a, b: lambda n: F.greatest(F.lit(1), F.floor(n * a / b))
    return rounded(arrivals.order_statistics(_order_times(spark, sf), {"p50": at(1, 2), "p90": at(9, 10), "p98": at(49, 50)}), "p50", "p90", "p98")


@q(f"{_T} SELECT trial, round(max(t), 6) + 0.0 AS finish FROM t GROUP BY trial")
def policy_waitall(spark, sf):
    return rounded(_times(spark).groupBy("trial").agg(F.max("t").alias("finish")), "finish")


@q(f"{_QS}, c AS (SELECT trial, max(CASE WHEN r = 3240 THEN t END) AS c FROM o GROUP BY trial) SELECT trial, round(max(greatest(c, CASE WHEN t > c THEN least(t, c + t2) ELSE 0 END)), 6) + 0.0 AS finish FROM o JOIN c USING (trial) GROUP BY trial")
def policy_speculative(spark, sf):
    """Relaunch after nine tenths are done; from the driver-side policy."""
    p = arrivals.Speculative(0.9)
    rows = [(k, p.finish(MODEL.draw(N, k, 0, 0), MODEL.draw(N, k, 0, 1))) for k in range(TRIALS)]
    return rounded(spark.createDataFrame(rows, "trial long, finish double"), "finish")


@q(f"{_QS} SELECT trial, round(max(CASE WHEN r = 3420 THEN t END), 6) + 0.0 AS finish, count(*) FILTER (r <= 3420) AS kept FROM o GROUP BY trial")
def policy_ignore(spark, sf):
    keep = F.col("r") <= 3420
    return rounded(_ranked(spark).groupBy("trial").agg(F.max(F.when(keep, F.col("t"))).alias("finish"), F.count_if(keep).alias("kept")), "finish")


@q(f"{_QS} SELECT trial, round(2 * max(CASE WHEN r = 3599 THEN t END), 6) + 0.0 AS finish FROM o GROUP BY trial")
def policy_gradient_code(spark, sf):
    p = arrivals.GradientCode(1)
    rows = [(k, p.finish(MODEL.draw(N, k), None)) for k in range(TRIALS)]
    return rounded(spark.createDataFrame(rows, "trial long, finish double"), "finish")


@q(f"{_T}, o AS (SELECT trial, worker // 12 AS tile, t, row_number() OVER (PARTITION BY trial, worker // 12 ORDER BY t, worker) AS r FROM t) SELECT trial, round(max(t), 6) + 0.0 AS finish FROM o WHERE r <= 10 GROUP BY trial")
def policy_sketch_any_n(spark, sf):
    """Ten of twelve blocks of each tile suffice."""
    w = Window.partitionBy("trial", "tile").orderBy("t", "worker")
    rows = _times(spark).withColumn("tile", F.floor(F.col("worker") / 12)).withColumn("r", F.row_number().over(w))
    return rounded(rows.where("r <= 10").groupBy("trial").agg(F.max("t").alias("finish")), "finish")


@q(f"{_T}, o AS (SELECT trial, worker // 3 AS g, t, row_number() OVER (PARTITION BY trial, worker // 3 ORDER BY t, worker) AS r FROM t) SELECT trial, round(max(t), 6) + 0.0 AS finish FROM o WHERE r <= 2 GROUP BY trial")
def policy_coded_single(spark, sf):
    """Groups of two workers and a parity worker; any two of three."""
    w = Window.partitionBy("trial", "g").orderBy("t", "worker")
    rows = _times(spark).withColumn("g", F.floor(F.col("worker") / 3)).withColumn("r", F.row_number().over(w))
    return rounded(rows.where("r <= 2").groupBy("trial").agg(F.max("t").alias("finish")), "finish")


@q(None)
def policy_coded_grid(spark, sf):
    """The product code's waiting time (peeling isn't SQL)."""
    p = arrivals.CodedGrid()
    rows = [(k, p.finish(MODEL.draw(N, k), None)) for k in range(TRIALS)]
    return rounded(spark.createDataFrame(rows, "trial long, finish double"), "finish")


_BLOCKS = f"{_T}, o AS (SELECT worker // 12 AS tile, worker % 12 AS block, row_number() OVER (PARTITION BY worker // 12 ORDER BY t, worker) AS r FROM t WHERE trial = 0 AND worker < 120)"


@q(f"{_BLOCKS} SELECT tile, block FROM o WHERE r <= 10")
def survivor_first_n(spark, sf):
    """Ten tiles of the first trial; ``survivor_first_n_whole`` has all."""
    rows = _times(spark).where("trial = 0 AND worker < 120").withColumn("tile", F.floor(F.col("worker") / 12))
    rows = rows.withColumn("r", F.row_number().over(Window.partitionBy("tile").orderBy("t", "worker")))
    return rows.where("r <= 10").select("tile", (F.col("worker") % 12).alias("block"))


@q(f"{_BLOCKS} SELECT tile, string_agg(block::VARCHAR, ',' ORDER BY block) AS blocks FROM o WHERE r <= 10 GROUP BY tile")
def survivor_lists(spark, sf):
    rows = QUERIES["survivor_first_n"][0](spark, sf)
    blocks = F.transform(F.sort_array(F.collect_list("block")), lambda b: b.cast("string"))
    return rows.groupBy("tile").agg(F.array_join(blocks, ",").alias("blocks"))


_TILES = f"{_T}, o AS (SELECT trial, worker // 12 AS tile, worker % 12 AS block, row_number() OVER (PARTITION BY trial, worker // 12 ORDER BY t, worker) AS r FROM t)"


@q(f"{_TILES} SELECT trial, tile, block FROM o WHERE r <= 10")
def survivor_first_n_whole(spark, sf):
    """All tiles of all trials."""
    rows = _times(spark).withColumn("tile", F.floor(F.col("worker") / 12))
    rows = rows.withColumn("r", F.row_number().over(Window.partitionBy("trial", "tile").orderBy("t", "worker")))
    return rows.where("r <= 10").select("trial", "tile", (F.col("worker") % 12).alias("block"))


@q(f"{_TILES} SELECT trial, tile, string_agg(block::VARCHAR, ',' ORDER BY block) AS blocks FROM o WHERE r <= 10 GROUP BY trial, tile")
def survivor_lists_whole(spark, sf):
    rows = QUERIES["survivor_first_n_whole"][0](spark, sf)
    blocks = F.transform(F.sort_array(F.collect_list("block")), lambda b: b.cast("string"))
    return rows.groupBy("trial", "tile").agg(F.array_join(blocks, ",").alias("blocks"))


# ------------------------------------------------------------------ line search and batches
_P = "(((i * 5 + 1) % 7 - 3) / 10.0)"


def p_fix(d):
    return [((i * 5 + 1) % 7 - 3) / 10.0 for i in range(d)]


_STEPS = f"""{emb()}, s AS (SELECT k, pow(4.0, -k) AS alpha FROM range(0, 6) r(k)), m AS (SELECT row_id, y, sum(v * {W_SQL}) AS t, sum(v * {_P}) AS u FROM a GROUP BY ALL),
l AS (SELECT alpha, avg(ln(1 + exp(-y * (t + alpha * u)))) AS loss FROM m, s GROUP BY alpha), f0 AS (SELECT avg(ln(1 + exp(-y * t))) AS f0, avg(-y * u / (1 + exp(y * t))) AS slope FROM m)"""


@q(f"{_STEPS} SELECT alpha, round(loss, 6) + 0.0 AS loss FROM l")
def linesearch_losses(spark, sf):
    """Losses of all six candidate steps in one pass."""
    from ..plans.optimise import scan
    from ..plans.problems import Logistic

    w, p = np.array(w_fix(64)), np.array(p_fix(64))
    s = scan(design.embeddings(spark, sf), Logistic(0.0), [w + a * p for a in GRID])
    return rounded(spark.createDataFrame([(a, float(v)) for a, v in zip(GRID, s.losses)], "alpha double, loss double"), "loss")


@q(f"{_STEPS} SELECT alpha, round(loss, 6) + 0.0 AS loss, loss <= f0 + alpha * 0.1 * slope AS ok FROM l, f0")
def linesearch_candidates(spark, sf):
    """The decrease test of each candidate, from margins and a table of six steps."""
    rows = design.embeddings(spark, sf).df.select("y", X.dot(F.col("x"), X.weights(w_fix(64))).alias("t"), X.dot(F.col("x"), X.weights(p_fix(64))).alias("u"))
    steps = F.broadcast(spark.createDataFrame([(a,) for a in GRID], "alpha double"))
    losses = rows.crossJoin(steps).groupBy("alpha").agg(F.avg(X.softplus(-F.col("y") * (F.col("t") + F.col("alpha") * F.col("u")))).alias("loss"))
    base = rows.agg(F.avg(X.softplus(-F.col("y") * F.col("t"))).alias("f0"), F.avg(-F.col("y") * F.col("u") * X.sigmoid(-F.col("y") * F.col("t"))).alias("slope"))
    out = losses.crossJoin(F.broadcast(base)).select("alpha", "loss", (F.col("loss") <= F.col("f0") + F.col("alpha") * 0.1 * F.col("slope")).alias("ok"))
    return rounded(out, "loss")


@q(f"{_STEPS} SELECT coalesce(max(CASE WHEN loss <= f0 + alpha * 0.1 * slope THEN alpha END), min(alpha)) AS alpha, count(*) FILTER (loss <= f0 + alpha * 0.1 * slope) = 0 AS failed FROM l, f0")
def linesearch_pick(spark, sf):
    c = QUERIES["linesearch_candidates"][0](spark, sf)
    return c.agg(F.coalesce(F.max(F.when(F.col("ok"), F.col("alpha"))), F.min("alpha")).alias("alpha"), (F.count_if("ok") == 0).alias("failed"))


@q(f"{_STEPS}, g AS (SELECT alpha, i, avg(v * -m.y / (1 + exp(m.y * (t + alpha * u)))) AS g FROM a JOIN m USING (row_id), s GROUP BY alpha, i) SELECT alpha, round(sum(g * g), 6) + 0.0 AS grad_sq FROM g GROUP BY alpha")
def linesearch_gradnorm(spark, sf):
    from ..plans.optimise import scan
    from ..plans.problems import Logistic

    w, p = np.array(w_fix(64)), np.array(p_fix(64))
    g = scan(design.embeddings(spark, sf), Logistic(0.0), (), [w + a * p for a in GRID]).gradients
    return rounded(spark.createDataFrame([(a, float(v @ v)) for a, v in zip(GRID, g)], "alpha double, grad_sq double"), "grad_sq")


def _part_gradient(where, seed):
    from ..functions.hashing import uniform_sql

    return f"{margin()} SELECT i, round(avg(v * -m.y / (1 + exp(m.y * t))), 6) + 0.0 AS g FROM a JOIN m USING (row_id) WHERE {uniform_sql('row_id', *seed)} {where} GROUP BY i"


def _hash_gradient(spark, sf, keep):
    from ..plans.optimise import scan
    from ..plans.problems import Logistic

    d = design.embeddings(spark, sf)
    g = scan(design.DesignMatrix(d.df.where(keep), 64), Logistic(0.0), (), [w_fix(64)]).gradients[0]
    return rounded(spark.createDataFrame([(i, float(x)) for i, x in enumerate(g)], "i long, g double"), "g")


@q(_part_gradient("< 0.95", (301, 0)))
def minibatch_gradient(spark, sf):
    from ..functions.hashing import uniform_col

    return _hash_gradient(spark, sf, uniform_col(F.col("row_id"), 301) < 0.95)


@q(_part_gradient("< 0.2", (701, 4)))
def sgd_gradient(spark, sf):
    """The minibatch of a fifth of the rows that iteration 4 draws."""
    from ..functions.hashing import uniform_col

    return _hash_gradient(spark, sf, uniform_col(F.col("row_id"), 701, 4) < 0.2)


@q(f"{margin()} SELECT i, round(avg(v * -m.y / (1 + exp(m.y * t))), 6) + 0.0 AS g FROM a JOIN m USING (row_id) WHERE {hash_sql('row_id', coefficients(97))} % 20 NOT IN (3, 11) GROUP BY i")
def ignore_stragglers_gradient(spark, sf):
    """Workers 3 and 11 of 20 are ignored; the mean is over the rows of the others."""
    from ..functions.hashing import hash_col

    return _hash_gradient(spark, sf, ~(hash_col(F.col("row_id"), coefficients(97)) % 20).isin(3, 11))


# ------------------------------------------------------------------ measures
@q(f"{margin()} SELECT CASE WHEN {hash_sql('row_id', coefficients(101))} % 4 = 0 THEN 'test' ELSE 'train' END AS split, round(avg(ln(1 + exp(-y * t))), 6) + 0.0 AS loss, round(avg((y <> CASE WHEN t > 0 THEN 1 ELSE -1 END)::INT), 6) + 0.0 AS err FROM m GROUP BY ALL")
def eval_test_error(spark, sf):
    from ..functions.hashing import hash_col

    rows = design.embeddings(spark, sf).df.withColumn("t", X.dot(F.col("x"), X.weights(w_fix(64))))
    split = F.when(hash_col(F.col("row_id"), coefficients(101)) % 4 == 0, "test").otherwise("train")
    wrong = F.col("y") != F.when(F.col("t") > 0, 1.0).otherwise(-1.0)
    return rounded(rows.groupBy(split.alias("split")).agg(F.avg(X.softplus(-F.col("y") * F.col("t"))).alias("loss"), F.avg(wrong.cast("int")).alias("err")), "loss", "err")


@q(f"{margin()} SELECT round(avg(ln(1 + exp(-y * t))), 6) + 0.0 AS loss FROM m")
def eval_train_loss(spark, sf):
    rows = design.embeddings(spark, sf).df.withColumn("t", X.dot(F.col("x"), X.weights(w_fix(64))))
    return rounded(rows.agg(F.avg(X.softplus(-F.col("y") * F.col("t"))).alias("loss")), "loss")


#: A fixed trace for the measures: (scheme, iterations, first gap, ratio, seconds a step).
_CURVES = (("first", 12, 0.5, 0.7, 3.0), ("exact", 6, 0.4, 0.05, 9.0), ("sketched", 9, 0.4, 0.2, 4.0))


def _trace(spark):
    rows = [("w", s, i, 0.25 + g * r**i, 0.0, 1.0, dt * i, 0.0, "") for s, n, g, r, dt in _CURVES for i in range(n)]
    from ..sources.tables import trace_frame

    return trace_frame(spark, rows)


_TR = "WITH t AS (" + " UNION ALL ".join(f"SELECT 'w' AS workload, '{s}' AS scheme, i AS it, (0.25 + {g} * pow({r}, i))::DOUBLE AS loss, ({dt} * i)::DOUBLE AS sim_s FROM range(0, {n}) x(i)" for s, n, g, r, dt in _CURVES) + ")"


@q(f"{_TR} SELECT workload, scheme, min(sim_s) AS t FROM t WHERE loss <= 0.26 GROUP BY ALL")
def trace_time_to_target(spark, sf):
    return measures.time_to_target(_trace(spark), 0.26)


@q(f"{_TR}, a AS (SELECT scheme, min(sim_s) AS t FROM t WHERE loss <= 0.26 GROUP BY ALL) SELECT 'w' AS workload, scheme, round(1 - t / (SELECT t FROM a WHERE scheme = 'exact'), 6) + 0.0 AS saved FROM a")
def trace_speed_up(spark, sf):
    return rounded(measures.speed_up(measures.time_to_target(_trace(spark), 0.26), "exact"), "saved")


@q(f"{_TR} SELECT workload, scheme, min(it) AS iters FROM t WHERE loss <= 0.26 GROUP BY ALL")
def trace_iters(spark, sf):
    return measures.iters_to_target(_trace(spark), 0.26)


@q(f"{_TR}, r AS (SELECT *, loss - 0.25 AS gap, lag(loss - 0.25) OVER (PARTITION BY scheme ORDER BY it) AS before FROM t) SELECT workload, scheme, it, round(gap / before, 5) + 0.0 AS ratio FROM r WHERE before > 0 AND gap > 0 AND it < 5")
def trace_rate(spark, sf):
    return measures.contraction(_trace(spark), 0.25).where("it < 5").select("workload", "scheme", "it", (F.round("ratio", 5) + 0.0).alias("ratio"))


@q(f"{_TR} SELECT scheme, it, sum(sim_s) OVER (PARTITION BY scheme ORDER BY it) AS total FROM t")
def trace_cumulative_time(spark, sf):
    w = Window.partitionBy("scheme").orderBy("it").rowsBetween(Window.unboundedPreceding, 0)
    return _trace(spark).select("scheme", "it", F.sum("sim_s").over(w).alias("total"))


@q(f"{_TR} SELECT scheme, it, round(min(loss) OVER (PARTITION BY scheme ORDER BY it), 6) + 0.0 AS best FROM t")
def trace_best_loss(spark, sf):
    return rounded(measures.best_so_far(_trace(spark)).select("scheme", "it", "best"), "best")


@q(f"{_TR}, g AS (SELECT (k * 5)::DOUBLE AS t FROM range(0, 8) r(k)), s AS (SELECT DISTINCT scheme FROM t) SELECT s.scheme, g.t, round(arg_max(t.loss, t.sim_s), 6) + 0.0 AS loss FROM s CROSS JOIN g JOIN t ON t.scheme = s.scheme AND t.sim_s <= g.t GROUP BY ALL")
def trace_asof(spark, sf):
    """Curves of different schemes aligned on one time grid."""
    grid = spark.range(8).select((F.col("id") * 5.0).alias("t"))
    return rounded(measures.aligned(_trace(spark), grid), "loss")


_ROUNDS = "WITH p AS (SELECT scheme, phase, (k + 1) * s AS s FROM (VALUES ('nag', 'gradient', 8.7), ('nag', 'search', 1.3), ('sketched', 'gradient', 2.0), ('sketched', 'hessian', 3.0)) v(scheme, phase, s), range(0, 3) r(k))"


@q(f"{_ROUNDS} SELECT scheme, phase, round(sum(s) / sum(sum(s)) OVER (PARTITION BY scheme), 6) + 0.0 AS share FROM p GROUP BY scheme, phase")
def trace_phase_share(spark, sf):
    rows = [(a, b, (k + 1) * s) for a, b, s in (("nag", "gradient", 8.7), ("nag", "search", 1.3), ("sketched", "gradient", 2.0), ("sketched", "hessian", 3.0)) for k in range(3)]
    return rounded(measures.phase_share(spark.createDataFrame(rows, "scheme string, phase string, s double")), "share")


@q(f"SELECT i, round({W_SQL}, 6) + 0.0 AS w FROM range(0, 64) r(i) ORDER BY abs({W_SQL}) DESC, i LIMIT 5")
def topk_weights(spark, sf):
    """The five largest weights: a top-k report."""
    w = spark.createDataFrame([(i, x) for i, x in enumerate(w_fix(64))], "i long, w double")
    return rounded(w.orderBy(F.abs("w").desc(), "i").limit(5), "w")


#: A model for each supplier: n rows are its lines, d features its distinct parts; tiles and
#: blocks of b = 50, N = 10 ceil(d / b) blocks of a sketch and a fifth as spares (e).
_JOBS = "WITH j AS (SELECT l_suppkey AS supplier, count(*) AS n, count(DISTINCT l_partkey) AS d FROM lineitem GROUP BY l_suppkey), g AS (SELECT *, ceil(d / 50.0)::BIGINT AS c, 10 * ceil(d / 50.0)::BIGINT AS blocks, 2 * ceil(d / 50.0)::BIGINT AS e, 50::BIGINT AS b FROM j)"


def _jobs(spark, sf):
    rows = tables.table(spark, sf, "lineitem", "l_suppkey", "l_partkey")
    j = rows.groupBy(F.col("l_suppkey").alias("supplier")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("l_partkey").alias("d"))
    c = F.ceil(F.col("d") / 50)
    return j.select("supplier", "n", "d", c.alias("c"), (10 * c).alias("blocks"), (2 * c).alias("e"), F.lit(50).cast("long").alias("b"))


@q(f"{_JOBS} SELECT supplier, d, pow(ceil(sqrt(blocks)), 2)::BIGINT + 2 * ceil(sqrt(blocks))::BIGINT + 1 AS matvec, (blocks + e) * c * c AS sketched, blocks * c * c AS exact, c * c AS reduction FROM g")
def cost_workers(spark, sf):
    """Workers of each phase, for a model of each supplier; as ``arrivals.workers`` counts them."""
    root, c = F.ceil(F.sqrt("blocks")), F.col("c")
    return _jobs(spark, sf).select("supplier", "d", (root * root + 2 * root + 1).alias("matvec"), ((F.col("blocks") + F.col("e")) * c * c).alias("sketched"), (F.col("blocks") * c * c).alias("exact"), (c * c).alias("reduction"))


_BYTES = "8 * d * 64 AS gradient, 8 * d * (d + 1) // 2 * 64 AS exact, 8 * (blocks + e) * b * d * least(64, greatest(1, n // b)) AS sketched, 16 * n * d AS encode"


def _bytes(jobs):
    """As ``arrivals.comm_bytes`` counts them, with 64 tasks."""
    return jobs.select("supplier", "n", "d", (F.col("d") * 512).alias("gradient"), F.expr("8 * d * (d + 1) div 2 * 64").alias("exact"), F.expr("8 * (blocks + e) * b * d * least(64L, greatest(1L, n div b))").alias("sketched"), F.expr("16 * n * d").alias("encode"))


@q(f"{_JOBS} SELECT supplier, n, d, {_BYTES} FROM g")
def cost_comm(spark, sf):
    """Bytes that a round exchanges, for a model of each supplier."""
    return _bytes(_jobs(spark, sf))


@q(f"{_JOBS}, c AS (SELECT {_BYTES} FROM g), s AS (SELECT unnest(['gradient', 'exact', 'sketched', 'local']) AS scheme, unnest([sum(gradient), sum(exact), sum(sketched), sum(gradient)])::BIGINT AS bytes FROM c) SELECT scheme, round(bytes / 1e9, 6) + 0.0 AS gb, ((bytes + 2999999999) // 3000000000)::BIGINT AS workers FROM s")
def cost_equalised(spark, sf):
    """Workers of each scheme for the rounds of all suppliers' models, at equal data for a
    worker (3000 MB)."""
    total = _bytes(_jobs(spark, sf)).agg(*[F.coalesce(F.sum(k), F.lit(0)).alias(k) for k in ("gradient", "exact", "sketched")])
    each = F.array(*[F.struct(F.lit(k).alias("scheme"), F.col(c).alias("bytes")) for k, c in (("gradient", "gradient"), ("exact", "exact"), ("sketched", "sketched"), ("local", "gradient"))])
    rows = total.select(F.inline(each))
    return rounded(rows.select("scheme", (F.col("bytes") / 1e9).alias("gb"), F.expr("(bytes + 2999999999L) div 3000000000L").alias("workers")), "gb")


@q("SELECT coalesce(l_returnflag, 'all') AS scheme, coalesce(l_linestatus, 'all') AS phase, round(sum(l_quantity)::DOUBLE, 6) + 0.0 AS s FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def cost_rollup(spark, sf):
    """Seconds by scheme and phase with their totals.  Order lines stand for rounds: the
    return flag for the scheme, the status for the phase, the quantity for the seconds."""
    out = tables.table(spark, sf, "lineitem", "l_returnflag", "l_linestatus", "l_quantity").rollup("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("s"))
    return rounded(out.select(F.coalesce("l_returnflag", F.lit("all")).alias("scheme"), F.coalesce("l_linestatus", F.lit("all")).alias("phase"), "s"), "s")
