"""Solvers, decoders, embeddings and convergence rates, measured."""

from __future__ import annotations

from itertools import combinations

import numpy as np
from pyspark.sql import functions as F

from ..functions import columns as X
from ..operators import coding
from ..operators.sketch import BlockSketch
from ..plans import arrivals, measures, optimise, race, semidefinite, solve
from ..plans.problems import Logistic, Softmax
from ..sources import design
from .base import Registry, emb, margin, rounded, w_fix
from .core import _ranked, _shard_gradients
from .runtime import _JOBS, _T, _jobs, _times

QUERIES = Registry()
q = QUERIES.add
LAM = 0.01


# ------------------------------------------------------------------ coded examples
@q(f"{margin()}, g AS (SELECT i, sum(v * -m.y / (1 + exp(m.y * t))) AS g FROM a JOIN m USING (row_id) GROUP BY i) SELECT l.w AS lost, i, round(g, 6) + 0.0 AS g FROM g, range(0, 4) l(w)")
def workload_w10(spark, sf):
    """Four workers with two shards each: whichever is lost, the rest give the gradient."""
    shards, code, out = _shard_gradients(spark, sf), coding.cyclic_code(4, 1), None
    for lost in range(4):
        part = coding.coded_sum(shards, code, [w for w in range(4) if w != lost]).select(F.lit(lost).cast("long").alias("lost"), "i", "g")
        out = part if out is None else out.unionByName(part)
    return rounded(out, "g")


@q(f"{margin()}, k AS (SELECT t, row_number() OVER (ORDER BY row_id) - 1 AS rank FROM m), h AS (SELECT ceil(count(*) / 2.0)::BIGINT AS half FROM m), z AS (SELECT p AS part, o AS offset_ FROM h, range(0, 2) a(p), unnest(range(0, half)) b(o)) SELECT l.w AS lost, z.part, z.offset_, round(coalesce(t, 0), 6) + 0.0 AS alpha FROM z CROSS JOIN h CROSS JOIN range(0, 3) l(w) LEFT JOIN k ON k.rank = z.part * h.half + z.offset_")
def workload_w11(spark, sf):
    """Three workers hold two halves and their sum: any two of them give the product.  A last
    half that is a row short ends in a row of zeros."""
    rows, n = _ranked(spark, sf)
    half = max(1, -(-n // 2))
    pad = spark.range(n, 2 * half).select(F.col("id").alias("rank"), F.array_repeat(F.lit(0.0), 64).alias("x"))
    part = rows.select("rank", "x").unionByName(pad).select(F.floor(F.col("rank") / half).cast("long").alias("part"), (F.col("rank") % half).alias("offset_"), "x")
    parity = part.groupBy("offset_").agg(F.max_by("x", -F.col("part")).alias("a"), F.max_by("x", "part").alias("b"))
    parity = parity.select(F.lit(2).cast("long").alias("part"), "offset_", F.zip_with("a", "b", lambda a, b: a + b).alias("x"))
    y = part.unionByName(parity).select("part", "offset_", X.dot(F.col("x"), X.weights(w_fix(64))).alias("y"))
    got = lambda lost, k: F.sum(F.when((F.col("part") == k) & (F.col("part") != lost), F.col("y")))
    wide = y.crossJoin(spark.range(3).withColumnRenamed("id", "lost")).groupBy("lost", "offset_").agg(*[got(F.col("lost"), k).alias(f"y{k}") for k in range(3)])
    first, second = F.coalesce("y0", F.col("y2") - F.col("y1")), F.coalesce("y1", F.col("y2") - F.col("y0"))
    both = F.array(*[F.struct(F.lit(k).cast("long").alias("part"), v.alias("alpha")) for k, v in enumerate((first, second))])
    return rounded(wide.select("lost", "offset_", F.inline(both)), "alpha")


@q("""WITH b AS (SELECT m, bit_count(m::BIGINT) AS k FROM range(0, 65536) r(m) WHERE bit_count(m::BIGINT) <= 4),
l AS (SELECT u.i AS i, v.i AS j FROM range(0, 4) u(i), range(0, 4) v(i) WHERE u.i < v.i),
x AS (SELECT (1 << (4 * r.i + c.i)) + (1 << (4 * r.i + c.j)) + (1 << (4 * r.j + c.i)) + (1 << (4 * r.j + c.j)) AS m FROM l r, l c)
SELECT k::BIGINT AS erased, count(*) AS patterns, count(*) FILTER (x.m IS NULL) AS decodable FROM b LEFT JOIN x USING (m) GROUP BY k""")
def measure_peel_patterns(spark, sf):
    """All losses of up to four of 16 coded blocks, and how many of them can be peeled."""
    cells, rows = [(r, c) for r in range(4) for c in range(4)], []
    for k in range(5):
        done = [coding.peel(set(lost), 3) is not None for lost in combinations(cells, k)]
        rows.append((k, len(done), sum(done)))
    return spark.createDataFrame(rows, "erased long, patterns long, decodable long")


@q(None)
def measure_decode_rate(spark, sf):
    """Share of random losses that can be peeled, by grid and loss probability."""
    rows = [(g * g, p, coding.decode_rate(g, p, trials=400)) for g in (3, 7, 10) for p in (0.02, 0.05, 0.1)]
    return spark.createDataFrame(rows, "blocks long, p double, rate double")


@q(f"{_T} SELECT trial, round(max(least(t, t2)), 6) + 0.0 AS finish FROM t GROUP BY trial")
def policy_replicate(spark, sf):
    """Two copies of each task; the first to end counts."""
    return rounded(_times(spark).groupBy("trial").agg(F.max(F.least("t", "t2")).alias("finish")), "finish")


@q(f"{_JOBS} SELECT supplier, n, d, (16 * b * b * ceil(n / 50.0)::BIGINT * c * c)::DOUBLE AS block, (16 * n * s * (ceil(d / s)::BIGINT) * (ceil(d / s)::BIGINT))::DOUBLE AS rowcol FROM (SELECT *, greatest(1, (b * b) // n) AS s FROM g)")
def cost_matmul_partition(spark, sf):
    """Bytes read for a Gram matrix by square blocks and by strips of whole columns, for a
    model of each supplier; as ``arrivals.matmul_bytes`` counts them."""
    rows = _jobs(spark, sf).withColumn("s", F.expr("greatest(1L, (b * b) div n)"))
    strips = F.ceil(F.col("d") / F.col("s"))
    block = F.col("b") * F.col("b") * 16 * F.ceil(F.col("n") / F.col("b")) * F.col("c") * F.col("c")
    return rows.select("supplier", "n", "d", block.cast("double").alias("block"), (F.col("n") * F.col("s") * 16 * strips * strips).cast("double").alias("rowcol"))


@q("SELECT d, multiple, b::BIGINT AS width, ceil(d * multiple / b)::BIGINT AS needed, ceil(0.04 * ceil(d * multiple / b))::BIGINT AS spare FROM (SELECT d::BIGINT AS d, k::BIGINT AS multiple, least(d, 2364)::DOUBLE AS b FROM (VALUES (300), (2000), (3000)) u(d), (VALUES (6), (10), (15)) v(k))")
def sketch_plan(spark, sf):
    """Blocks, their width and spares from features, memory and the share of slow workers."""
    plans = [(d, k, BlockSketch.plan(d, k)) for d in (300, 2000, 3000) for k in (6, 10, 15)]
    return spark.createDataFrame([(d, k, s.width, s.n, s.spare) for d, k, s in plans], "d long, multiple long, width long, needed long, spare long")


# ------------------------------------------------------------------ solvers
_H2 = f"""{emb(2)}, h AS (SELECT sum(CASE WHEN i = 0 THEN v END) AS a, sum(CASE WHEN i = 1 THEN v END) AS b, y FROM a GROUP BY row_id, y),
s AS (SELECT avg(a * a) / 4 + {LAM} AS h11, avg(a * b) / 4 AS h12, avg(b * b) / 4 + {LAM} AS h22, avg(-a * y) / 2 AS g1, avg(-b * y) / 2 AS g2 FROM h)"""


def _newton_system(spark, sf):
    """Hessian and gradient of the two-coordinate logistic loss at zero."""
    s = optimise.scan(design.embeddings(spark, sf).head(2), Logistic(LAM), (), [np.zeros(2)], np.zeros(2))
    return s.gram, s.gradients[0]


@q(f"{_H2} SELECT solver, round((h22 * g1 - h12 * g2) / (h11 * h22 - h12 * h12), 6) + 0.0 AS p1, round((h11 * g2 - h12 * g1) / (h11 * h22 - h12 * h12), 6) + 0.0 AS p2 FROM s, (VALUES ('cholesky'), ('pseudo-inverse'), ('conjugate gradients'), ('minimum residual'), ('distributed conjugate gradients')) v(solver)")
def solver_direction(spark, sf):
    """One Newton system by each solver."""
    h, g = _newton_system(spark, sf)
    tiles = spark.createDataFrame([(i, j, float(h[i, j])) for i in range(2) for j in range(i, 2)], "i int, j int, h double")
    found = {
        "cholesky": solve.solve_spd(h, g),
        "pseudo-inverse": solve.pinv_solve(h, g),
        "conjugate gradients": solve.cg(lambda p: h @ p, g),
        "minimum residual": solve.minres(lambda p: h @ p, g),
        "distributed conjugate gradients": solve.cg_distributed(tiles, g),
    }
    return rounded(spark.createDataFrame([(k, float(v[0]), float(v[1])) for k, v in found.items()], "solver string, p1 double, p2 double"), "p1", "p2")


@q(f"{_H2} SELECT round((h11 + h22 - sqrt((h11 - h22) ** 2 + 4 * h12 * h12)) / 2, 6) + 0.0 AS least, round((h11 + h22 + sqrt((h11 - h22) ** 2 + 4 * h12 * h12)) / 2, 6) + 0.0 AS largest FROM s")
def measure_constants(spark, sf):
    """Extreme eigenvalues of the Hessian: the constants of the rate bounds."""
    h, g = _newton_system(spark, sf)
    c = measures.constants(h, g)
    return rounded(spark.createDataFrame([(c["k"], c["M"])], "least double, largest double"), "least", "largest")


@q(None)
def step_fixed_tuned(spark, sf):
    """The constant step that a short trial of exact Newton steps picks, and its loss."""
    data = design.embeddings(spark, sf)
    data = design.DesignMatrix(data.df.cache(), 64)
    best = optimise.tune_fixed_step(data, Logistic(LAM), grid=(1.0, 0.5, 0.25), iters=2)
    fit = optimise.exact_newton(data, Logistic(LAM), step=optimise.FixedStep(best), iters=4)
    data.df.unpersist()
    return spark.createDataFrame([(best, float(fit.loss))], "step double, loss double")


@q(None)
def semidefinite_barrier(spark, sf):
    """A box as a semidefinite program, by exact and sketched barrier steps."""
    box = np.diag([1.0, 1.0, 0.0, 0.0])
    sides = [np.diag([-1.0, 0, 1, 0]), np.diag([0, -1.0, 0, 1])]
    rows = []
    for name, sk in (("exact", None), ("sketched", BlockSketch(6, 0, 4, 1))):
        x = semidefinite.solve(box, sides, [-1.0, -2.0], [0.4, 0.4], sketch=sk)
        rows.append((name, float(x[0]), float(x[1])))
    return spark.createDataFrame(rows, "scheme string, x1 double, x2 double")


@q(None)
def race_any_n(spark, sf):
    """A sketched Hessian from the first blocks to end of real jobs: its relative error."""
    data, problem, w = design.embeddings(spark, sf), Logistic(LAM), np.zeros(64)
    sk = BlockSketch(6, 2, 512, 3)
    used, rows = race.raced_sketch(spark, data, problem, w, sk)
    exact = optimise.scan(data, problem, (), (), w)
    near = sum(rows[k].T @ rows[k] for k in used) / (len(used) * exact.n) + problem.reg_hessian(w)
    return spark.createDataFrame([(len(used), measures.embedding_eps(exact.gram, near))], "blocks long, eps double")


# ------------------------------------------------------------------ embeddings and rates
@q(None)
def measure_embedding_eps(spark, sf):
    """Error of the sketched Hessian over 20 draws by sketch size, and how often it passes a
    half: the draws are disjoint blocks of one sketch, so a size takes one scan."""
    data, problem, w, draws = design.embeddings(spark, sf), Logistic(LAM), np.zeros(64), 20
    data = design.DesignMatrix(data.df.cache(), 64)
    h, rows = optimise.scan(data, problem, hessian_at=w).gram, []
    for multiple in (2, 5, 10, 15, 50):
        s = optimise.scan(data, problem, hessian_at=w, sketch=BlockSketch(multiple * draws, 0, 64, 31))
        eps = [measures.embedding_eps(h, optimise.sketched_hessian(s, problem, w, list(range(k * multiple, (k + 1) * multiple)))) for k in range(draws)]
        rows.append((multiple, float(np.median(eps)), max(eps), measures.failure_rate(eps, 0.5)))
    data.df.unpersist()
    return spark.createDataFrame(rows, "multiple long, eps_median double, eps_largest double, failures double")


@q(None)
def measure_rate_bounds(spark, sf):
    """Each step's contraction of the loss gap (or, weakly convex, of the squared gradient
    norm) beside the guaranteed one, and whether the conditions of the local bound hold."""
    data, beta, rows = design.embeddings(spark, sf), 0.1, []
    data = design.DesignMatrix(data.df.cache(), 64)
    problem = Logistic(LAM)
    best = optimise.exact_newton(data, problem, iters=8)
    s = optimise.scan(data, problem, (), [best.w], best.w)
    c = measures.constants(s.gram, s.gradients[0])
    sk = BlockSketch.of(3200, 128, 0.0, seed=4)
    eps = measures.embedding_eps(s.gram, optimise.sketched_hessian(optimise.scan(data, problem, (), (), best.w, sk), problem, best.w, list(range(sk.blocks))))
    fit = optimise.sketched_newton(data, problem, sk, iters=4, step=optimise.ArmijoF())
    gaps = [max(t["loss"] - best.loss, 1e-16) for t in fit.trace]
    for t, a, b in zip(fit.trace, gaps, gaps[1:]):
        bound = measures.global_rate(t["step"], beta, c["k"], c["M"], eps)
        rows.append(("strong", t["it"], float(b / a), float(bound), bool(b <= bound * a + 1e-12), bool(measures.local_bound_applies(eps, c["k"], c["M"]))))
    many, soft = design.embeddings_multi(spark, sf), Softmax(10)
    many = design.DesignMatrix(many.df.cache(), 64, many.classes)
    fit = optimise.newton(many, soft, iters=3)
    for t, u in zip(fit.trace, fit.trace[1:]):
        here = optimise.scan(many, soft, (), [t["w"]], t["w"])
        c = measures.constants(here.gram, here.gradients[0])
        bound = measures.weak_rate(t["step"], beta, c["nu"], 0.0, c["eta"], c["M"])
        seen = (u["grad_norm"] / t["grad_norm"]) ** 2
        rows.append(("weak", t["it"], float(seen), float(bound), bool(seen <= bound + 1e-12), True))
    data.df.unpersist()
    many.df.unpersist()
    return spark.createDataFrame(rows, "kind string, it long, seen double, bound double, holds boolean, local_applies boolean")
