"""Whole fits: small ones with recursive or unrolled SQL twins, and the workloads."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions.hashing import coefficients, hash_sql
from ..operators import sketch
from ..operators.sketch import BlockSketch
from ..plans import optimise, workloads
from ..plans.coded import CodedPair
from ..plans.problems import Logistic, Softmax
from ..sources import design
from .base import Registry, rounded, w_fix
from .core import QUERIES as CORE
from .runtime import _T

QUERIES = Registry()
q = QUERIES.add
LAM = 0.01
_E2 = "e AS (SELECT vec_id AS id, CASE WHEN label < 5 THEN 1.0 ELSE -1.0 END::DOUBLE AS y, embedding[1]::DOUBLE AS a, embedding[2]::DOUBLE AS b, embedding[3]::DOUBLE AS c FROM embeddings)"


def _iterates(spark, fit_one, iters, d):
    """(it, w1 ..): the iterates, from fits that stop after each number of steps."""
    rows = [(k, *[float(v) for v in fit_one(k)]) for k in range(iters + 1)]
    names = [f"w{i + 1}" for i in range(d)]
    return rounded(spark.createDataFrame(rows, "it long, " + ", ".join(f"{n} double" for n in names)), *names)


@q(f"""WITH RECURSIVE {_E2}, w AS (SELECT 0::BIGINT AS it, 0.0::DOUBLE AS w1, 0.0::DOUBLE AS w2, 0.0::DOUBLE AS w3 UNION ALL
SELECT it + 1, w1 - 4.0 * (g1 + {LAM} * w1), w2 - 4.0 * (g2 + {LAM} * w2), w3 - 4.0 * (g3 + {LAM} * w3) FROM (
SELECT it, any_value(w1) AS w1, any_value(w2) AS w2, any_value(w3) AS w3, avg(a * s) AS g1, avg(b * s) AS g2, avg(c * s) AS g3 FROM (
SELECT it, w1, w2, w3, a, b, c, -y / (1 + exp(y * (w1 * a + w2 * b + w3 * c))) AS s FROM w, e WHERE it < 6) GROUP BY it))
SELECT it, round(w1, 6) + 0.0 AS w1, round(w2, 6) + 0.0 AS w2, round(w3, 6) + 0.0 AS w3 FROM w""")
def logistic_gd_3d(spark, sf):
    """Gradient descent with a fixed step on three coordinates."""
    d = design.embeddings(spark, sf).head(3)
    d = design.DesignMatrix(d.df.cache(), 3)
    w, out = [0.0] * 3, [[0.0] * 3]
    for _ in range(6):
        w = optimise.first_order(d, Logistic(LAM), w0=w, rule=optimise.FixedStep(4.0), iters=1).w.tolist()
        out.append(w)
    d.df.unpersist()
    return _iterates(spark, lambda k: out[k], 6, 3)


@q(f"""WITH RECURSIVE {_E2}, w AS (SELECT 0::BIGINT AS it, 0.0::DOUBLE AS w1, 0.0::DOUBLE AS w2, 0.0::DOUBLE AS p1, 0.0::DOUBLE AS p2, 1.0::DOUBLE AS t UNION ALL
SELECT it + 1, v1 - 4.0 * (g1 + {LAM} * v1), v2 - 4.0 * (g2 + {LAM} * v2), w1, w2, u FROM (
SELECT it, any_value(w1) AS w1, any_value(w2) AS w2, any_value(u) AS u, any_value(v1) AS v1, any_value(v2) AS v2, avg(a * -y / (1 + exp(y * (v1 * a + v2 * b)))) AS g1, avg(b * -y / (1 + exp(y * (v1 * a + v2 * b)))) AS g2 FROM (
SELECT it, w1, w2, u, w1 + (t - 1) / u * (w1 - p1) AS v1, w2 + (t - 1) / u * (w2 - p2) AS v2 FROM (SELECT *, (1 + sqrt(1 + 4 * t * t)) / 2 AS u FROM w) WHERE it < 6), e GROUP BY it))
SELECT it, round(w1, 6) + 0.0 AS w1, round(w2, 6) + 0.0 AS w2 FROM w""")
def logistic_nag_2d(spark, sf):
    """Accelerated gradient descent with a fixed step on two coordinates."""
    d = design.DesignMatrix(design.embeddings(spark, sf).head(2).df.cache(), 2)
    fits = [optimise.nesterov(d, Logistic(LAM), rule=optimise.FixedStep(4.0), iters=k).w for k in range(7)]
    d.df.unpersist()
    return _iterates(spark, lambda k: fits[k], 6, 2)


def _unrolled(hessian, iters):
    """Newton on two coordinates as a chain of CTEs; ``hessian(k)``: CTE text for h11, h12,
    h22 (data part) at step k from w{k} and e."""
    parts = ["w0 AS (SELECT 0.0::DOUBLE AS w1, 0.0::DOUBLE AS w2)"]
    for k in range(iters):
        parts.append(f"g{k} AS (SELECT any_value(w1) AS w1, any_value(w2) AS w2, avg(a * -y / (1 + exp(y * (w1 * a + w2 * b)))) + {LAM} * any_value(w1) AS g1, avg(b * -y / (1 + exp(y * (w1 * a + w2 * b)))) + {LAM} * any_value(w2) AS g2 FROM e, w{k})")
        parts += hessian(k)
        parts.append(f"w{k + 1} AS (SELECT w1 - (h22 * g1 - h12 * g2) / (h11 * h22 - h12 * h12) AS w1, w2 - (h11 * g2 - h12 * g1) / (h11 * h22 - h12 * h12) AS w2 FROM g{k}, (SELECT h11 + {LAM} AS h11, h12, h22 + {LAM} AS h22 FROM h{k}))")
    rows = " UNION ALL ".join(f"SELECT {k}::BIGINT AS it, round(w1, 6) + 0.0 AS w1, round(w2, 6) + 0.0 AS w2 FROM w{k}" for k in range(iters + 1))
    return f"WITH {_E2}, " + ", ".join(parts) + " " + rows


def _root(k):
    return f"r{k} AS (SELECT id, a * sqrt(s * (1 - s)) AS a, b * sqrt(s * (1 - s)) AS b FROM (SELECT id, a, b, 1 / (1 + exp(-(w1 * a + w2 * b))) AS s FROM e, w{k}))"


def _exact(k):
    return [_root(k), f"h{k} AS (SELECT avg(a * a) AS h11, avg(a * b) AS h12, avg(b * b) AS h22 FROM r{k})"]


SKETCH = BlockSketch(8, 2, 8, 4)


def _used(it):
    s = SKETCH.fresh(it)
    t = optimise.FUNCTIONS.model.draw(s.blocks, it, 5)
    return s, sorted(np.argsort(t, kind="stable")[: s.n].tolist())


def _sketched(k):
    s, used = _used(k)
    each = " UNION ALL ".join(f"SELECT {b} AS block, a, b, {hash_sql('id', s.coef(b))} AS h FROM r{k}" for b in used)
    sums = f"s{k} AS (SELECT block, (h // 2) % {s.width} AS bucket, sum((1 - 2 * (h % 2)) * a) AS a, sum((1 - 2 * (h % 2)) * b) AS b FROM ({each}) GROUP BY ALL)"
    return [_root(k), sums, f"h{k} AS (SELECT sum(a * a) / {s.n}.0 / n AS h11, sum(a * b) / {s.n}.0 / n AS h12, sum(b * b) / {s.n}.0 / n AS h22 FROM s{k}, (SELECT count(*) AS n FROM e) GROUP BY n)"]


def _newton_2d(sketch, coded=False):
    def run(spark, sf):
        d = design.DesignMatrix(design.embeddings(spark, sf).head(2).df.cache(), 2)
        pair = CodedPair.encode(d, 3, 1) if coded else None
        trace = optimise.newton(d, Logistic(LAM), sketch=sketch, iters=5, tol=0.0, guard=False, coded=pair).trace
        fits = [t["w"] for t in trace]
        d.df.unpersist()
        if pair:
            pair.release()
        return _iterates(spark, lambda k: fits[k], 5, 2)

    return run


q(_unrolled(_exact, 5), "logistic_exact_newton_2d")(_newton_2d(None))
q(_unrolled(_sketched, 5), "logistic_fit_2d")(_newton_2d(SKETCH))
q(_unrolled(_sketched, 5), "logistic_fit_coded_2d")(_newton_2d(SKETCH, coded=True))


@q(CORE["logistic_gradient"][1])
def coded_gradient(spark, sf):
    """The gradient by two coded rounds, each without the blocks that come last."""
    pair = CodedPair.encode(design.embeddings(spark, sf), 3, 3)
    g = pair.evaluate(Logistic(LAM), np.array(w_fix(64)), it=4).gradient
    pair.release()
    return rounded(spark.createDataFrame([(i, float(v)) for i, v in enumerate(g)], "i long, g double"), "g")


@q(CORE["logistic_gradient"][1])
def gradient_code_in_a_fit(spark, sf):
    """The gradient that a gradient-coded fit decodes: 12 workers, the three slowest lost."""
    d, workers = design.embeddings(spark, sf), 12
    g = optimise.coded_gradient(d, Logistic(LAM), np.array(w_fix(64)), workers, 3, optimise._worker(workers), optimise.FUNCTIONS.model.draw(workers, 2, 0))
    return rounded(spark.createDataFrame([(i, float(v)) for i, v in enumerate(g)], "i long, g double"), "g")


_RAN = f"a AS (SELECT vec_id AS id, label, [embedding[1]::DOUBLE, embedding[2]::DOUBLE] AS x FROM embeddings), z AS (SELECT id, x, k, exp(x[1] * ((2 * k * 7 + 3) % 11 - 5) / 10.0 + x[2] * (((2 * k + 1) * 7 + 3) % 11 - 5) / 10.0) AS e FROM a, range(0, 10) c(k))"
_RAN += ", p AS (SELECT id, x, k, e / sum(e) OVER (PARTITION BY id) AS p FROM z)"
_RAN += ", r AS (SELECT s.id, s.k AS s, t.k * 2 + f.f AS i, sqrt(s.p) * ((s.k = t.k)::INT - t.p) * s.x[f.f + 1] AS v FROM p s JOIN p t ON s.id = t.id, range(0, 2) f(f))"


@q(f"WITH {_RAN} SELECT u.i, v.i AS j, round(sum(u.v * v.v), 6) + 0.0 AS h FROM r u JOIN r v ON u.id = v.id AND u.s = v.s AND u.i <= v.i GROUP BY ALL")
def softmax_root_gram(spark, sf):
    """Gram matrix of the softmax root rows (ten for each example, ten classes, two
    coordinates): the Hessian that a sketch of these rows approximates."""
    d = design.embeddings_multi(spark, sf).head(2)
    w = np.array(w_fix(20))
    root = optimise.root_rows(d, Softmax(10), w)
    h = sketch.gram_exact(root, 20)
    rows = [(i, j, float(h[i, j])) for i in range(20) for j in range(i, 20)]
    return rounded(spark.createDataFrame(rows, "i long, j long, h double"), "h")


@q(_unrolled(_sketched, 1).split(" SELECT 0::BIGINT AS it")[0] + """ SELECT 'a' AS k, round(h11, 6) + 0.0 AS h FROM h0 UNION ALL SELECT 'b', round(h12, 6) + 0.0 FROM h0 UNION ALL SELECT 'c', round(h22, 6) + 0.0 FROM h0""")
def sketched_hessian_tiles(spark, sf):
    """The sketched Hessian by distributed tiles of one column each, two blocks at a time."""
    d = design.embeddings(spark, sf).head(2)
    s, used = _used(0)
    h = optimise.tiled_hessian(d, Logistic(0.0), np.zeros(2), s, used, float(d.df.count()), tile=1)
    return rounded(spark.createDataFrame([("a", float(h[0, 0])), ("b", float(h[0, 1])), ("c", float(h[1, 1]))], "k string, h double"), "h")

_LOCAL = f"""WITH {_E2}, p AS (SELECT a, y, 1 / (1 + exp(-0.3 * a)) AS s, {hash_sql('id', coefficients(97))} % 4 AS worker FROM e), g AS (SELECT avg(a * -y / (1 + exp(y * 0.3 * a))) + {LAM} * 0.3 AS g FROM p)
SELECT worker::BIGINT AS worker, count(*) AS n, round(-any_value(g) / (avg(a * a * s * (1 - s)) + {LAM}), 6) + 0.0 AS p1 FROM p, g GROUP BY worker"""


_LOCAL2 = f"""WITH {_E2}, p AS (SELECT a, b, y, 1 / (1 + exp(-(0.3 * a - 0.2 * b))) AS s, {hash_sql('id', coefficients(97))} % 4 AS worker FROM e),
g AS (SELECT avg(a * -y / (1 + exp(y * (0.3 * a - 0.2 * b)))) + {LAM} * 0.3 AS g1, avg(b * -y / (1 + exp(y * (0.3 * a - 0.2 * b)))) - {LAM} * 0.2 AS g2 FROM p),
h AS (SELECT worker, count(*) AS n, avg(a * a * s * (1 - s)) + {LAM} AS h11, avg(a * b * s * (1 - s)) AS h12, avg(b * b * s * (1 - s)) + {LAM} AS h22 FROM p GROUP BY worker)
SELECT worker::BIGINT AS worker, n, round(-(h22 * g1 - h12 * g2) / (h11 * h22 - h12 * h12), 6) + 0.0 AS p1, round(-(h11 * g2 - h12 * g1) / (h11 * h22 - h12 * h12), 6) + 0.0 AS p2 FROM h, g"""


@q(_LOCAL2)
def local_newton_shards_2d(spark, sf):
    """Each of four workers' own Newton direction on two coordinates."""
    d, w = design.embeddings(spark, sf).head(2), np.array([0.3, -0.2])
    g = optimise.scan(d, Logistic(LAM), (), [w]).gradients[0]
    rows = optimise.local_directions(optimise.by_worker(d, 4), 2, Logistic(LAM), w, g, 4).collect()
    out = [(r["worker"], r["n"], *map(float, np.frombuffer(r["v"], np.float64))) for r in rows]
    return rounded(spark.createDataFrame(out, "worker long, n long, p1 double, p2 double"), "p1", "p2")


@q(_LOCAL)
def local_newton_shards_1d(spark, sf):
    """Each of four workers' own Newton direction on one coordinate."""
    import pyarrow as pa

    d = design.embeddings(spark, sf).head(1)
    w = np.array([0.3])
    g = optimise.scan(d, Logistic(LAM), (), [w]).gradients[0]
    rows = optimise.local_directions(optimise.by_worker(d, 4), 1, Logistic(LAM), w, g, 4)

    def unpack(batches):
        for b in batches:
            v = [float(np.frombuffer(x, np.float64)[0]) for x in b.column("v").to_pylist()]
            yield pa.record_batch([b.column("worker"), b.column("n"), pa.array(v, pa.float64())], names=["worker", "n", "p1"])

    return rounded(rows.mapInArrow(unpack, "worker int, n long, p1 double"), "p1")


@q(None)
def logistic_sketched_fit(spark, sf):
    """The whole method on all 64 coordinates: data encoded once, gradients by two coded
    rounds that wait for no slow block, sketched Hessians from any N blocks; its trace."""
    d = design.embeddings(spark, sf)
    d = design.DesignMatrix(d.df.cache(), 64)
    pair = CodedPair.encode(d)
    fit = optimise.sketched_newton(d, Logistic(LAM), BlockSketch.of(640, 64, 0.2), iters=6, coded=pair)
    pair.release()
    from ..sources.tables import trace_frame

    return trace_frame(spark, fit.rows("logistic"))


_TWINS = {
    "w09": f"{_T} SELECT 'jobs' AS workload, 'arrivals' AS scheme, trial::BIGINT AS it, round(quantile_cont(t, 0.5), 6) + 0.0 AS loss, round(avg((t > 145)::INT), 6) + 0.0 AS grad_norm, round(max(t), 6) + 0.0 AS step, 0.0::DOUBLE AS sim_s, 0.0::DOUBLE AS wall_s, 'loss=median grad_norm=slow share step=longest' AS note, NULL::DOUBLE AS test_loss, NULL::DOUBLE AS test_error FROM t GROUP BY trial"
}
for _name in workloads.NAMES:
    q(_TWINS.get(_name), f"workload_{_name}")(lambda spark, sf, _name=_name: workloads.run(spark, sf, _name))
