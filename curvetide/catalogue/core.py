"""Single evaluations: margins, objectives, gradients, Hessians, sketches, codes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import columns as X
from ..functions.hashing import hash_sql
from ..operators import coding, sketch
from ..operators.vectors import sum_arrays
from ..plans.optimise import scan
from ..plans.problems import Logistic, Ridge, Softmax, SquaredHinge
from ..sources import design, tables
from .base import SIG, W_SQL, Registry, emb, margin, rounded, w_fix

QUERIES = Registry()
q = QUERIES.add
LAM = 0.01


def _vector(spark, v, name="g"):
    return rounded(spark.createDataFrame([(i, float(x)) for i, x in enumerate(v)], f"i long, {name} double"), name)


def _upper(spark, h, digits=6):
    d = len(h)
    rows = [(i, j, float(h[i, j])) for i in range(d) for j in range(i, d)]
    return spark.createDataFrame(rows, "i long, j long, h double").withColumn("h", F.round("h", digits) + 0.0)


# ------------------------------------------------------------------ margins and objectives
@q(f"{margin()} SELECT row_id AS vec_id, round(t, 6) + 0.0 AS alpha FROM m")
def margin_dot(spark, sf):
    d = design.embeddings(spark, sf)
    return rounded(d.df.select(F.col("row_id").alias("vec_id"), X.dot(F.col("x"), X.weights(w_fix(64))).alias("alpha")), "alpha")


@q(QUERIES["margin_dot"][1])
def matvec_long_join(spark, sf):
    """The form for weights too long for a literal: entries joined with weights by place."""
    long = design.embeddings(spark, sf).df.select("row_id", F.posexplode("x").alias("i", "v"))
    w = spark.createDataFrame([(i, x) for i, x in enumerate(w_fix(64))], "i int, w double")
    return rounded(long.join(w, "i").groupBy(F.col("row_id").alias("vec_id")).agg(F.sum(F.col("v") * F.col("w")).alias("alpha")), "alpha")


@q("""WITH t AS (SELECT c_custkey, CASE c_custkey % 3 WHEN 0 THEN c_acctbal WHEN 1 THEN c_acctbal / 100 ELSE -c_acctbal / 1000 END AS t FROM customer)
SELECT c_custkey, t, round(CASE WHEN t > 0 THEN t + ln(1 + exp(-t)) ELSE ln(1 + exp(t)) END, 6) + 0.0 AS softplus, round(CASE WHEN t > 0 THEN 1 / (1 + exp(-t)) ELSE exp(t) / (1 + exp(t)) END, 6) + 0.0 AS sigmoid FROM t""")
def math_logistic_stable(spark, sf):
    """On account balances, as they are (up to 10,000, where plain forms overflow) or smaller."""
    X.register(spark)
    b, k = F.col("c_acctbal"), F.col("c_custkey") % 3
    t = tables.table(spark, sf, "customer", "c_custkey", "c_acctbal").select("c_custkey", F.when(k == 0, b).when(k == 1, b / 100).otherwise(-b / 1000).alias("t"))
    return t.select("c_custkey", "t", X.r6(F.expr("softplus(t)")).alias("softplus"), X.r6(F.expr("sigmoid(t)")).alias("sigmoid"))


@q(f"{margin()} SELECT round(avg(ln(1 + exp(-y * t))) + {LAM} / 2 * (SELECT sum({W_SQL} * {W_SQL}) FROM range(0, 64) r(i)), 6) + 0.0 AS loss FROM m")
def logistic_loss(spark, sf):
    s = scan(design.embeddings(spark, sf), Logistic(LAM), [w_fix(64)])
    return rounded(spark.createDataFrame([(float(s.losses[0]),)], "loss double"), "loss")


@q(f"{margin()} SELECT row_id AS vec_id, round(-y / (1 + exp(y * t)), 6) + 0.0 AS beta, round({SIG} * (1 - {SIG}), 6) + 0.0 AS gamma FROM m")
def logistic_beta_gamma(spark, sf):
    rows = design.embeddings(spark, sf).df.withColumn("t", X.dot(F.col("x"), X.weights(w_fix(64))))
    s = X.sigmoid(F.col("t"))
    return rounded(rows.select(F.col("row_id").alias("vec_id"), (-F.col("y") * X.sigmoid(-F.col("y") * F.col("t"))).alias("beta"), (s * (1 - s)).alias("gamma")), "beta", "gamma")


_GRADIENT = f"{margin()} SELECT i, round(avg(v * -m.y / (1 + exp(m.y * t))) + {LAM} * {W_SQL}, 6) + 0.0 AS g FROM a JOIN m USING (row_id) GROUP BY i"


@q(_GRADIENT)
def logistic_gradient(spark, sf):
    return _vector(spark, scan(design.embeddings(spark, sf), Logistic(LAM), (), [w_fix(64)]).gradients[0])


@q(_GRADIENT)
def logistic_gradient_sql(spark, sf):
    """The same by JVM operators only: entries weighed by beta and summed by place."""
    rows = design.embeddings(spark, sf).df.withColumn("t", X.dot(F.col("x"), X.weights(w_fix(64))))
    beta = -F.col("y") * X.sigmoid(-F.col("y") * F.col("t"))
    long = rows.select(beta.alias("b"), F.posexplode("x").alias("i", "v"))
    return rounded(long.groupBy("i").agg((F.avg(F.col("v") * F.col("b")) + LAM * (F.pmod(F.col("i") * 7 + 3, F.lit(11)) - 5) / 10.0).alias("g")), "g")


_HESSIAN = f"{margin(16)}, g AS (SELECT row_id, {SIG} * (1 - {SIG}) AS s FROM m)"


@q(f"{_HESSIAN} SELECT p.i, r.i AS j, round(avg(s * p.v * r.v) + CASE WHEN p.i = r.i THEN {LAM} ELSE 0 END, 6) + 0.0 AS h FROM a p JOIN a r USING (row_id) JOIN g USING (row_id) WHERE p.i <= r.i GROUP BY p.i, r.i")
def logistic_hessian(spark, sf, d=16):
    return _upper(spark, scan(design.embeddings(spark, sf).head(d), Logistic(LAM), hessian_at=w_fix(d)).gram)


def _softmax(qd):
    return f"""{emb(qd)}, k AS (SELECT unnest(range(0, 10)) AS k),
s AS (SELECT row_id, label, k, sum(v * (((i * 7 + k * 5 + 3) % 11 - 5) / 10.0)) AS t FROM a, k GROUP BY ALL),
z AS (SELECT row_id, label, k, t, exp(t) / sum(exp(t)) OVER (PARTITION BY row_id) AS p, ln(sum(exp(t)) OVER (PARTITION BY row_id)) AS lse FROM s)"""


def w_soft(d):
    return [((i * 7 + k * 5 + 3) % 11 - 5) / 10.0 for k in range(10) for i in range(d)]


@q(f"{_softmax(64)} SELECT round(sum(lse - t), 5) + 0.0 AS loss FROM z WHERE k = label")
def softmax_loss(spark, sf):
    s = scan(design.embeddings_multi(spark, sf), Softmax(10), [w_soft(64)])
    return spark.createDataFrame([(round(float(s.losses[0]), 5),)], "loss double")


@q(f"{_softmax(64)} SELECT k, i, round(sum(v * (p - CASE WHEN k = a.label THEN 1 ELSE 0 END)), 6) + 0.0 AS g FROM a JOIN z USING (row_id) GROUP BY k, i")
def softmax_gradient(spark, sf):
    g = scan(design.embeddings_multi(spark, sf), Softmax(10), (), [w_soft(64)]).gradients[0].reshape(10, 64)
    return rounded(spark.createDataFrame([(k, i, float(g[k, i])) for k in range(10) for i in range(64)], "k long, i long, g double"), "g")


_BLOCKS = f"""{_softmax(8)} SELECT x.k, y.k AS l, p.i, r.i AS j, round(sum(p.v * r.v * (CASE WHEN x.k = y.k THEN x.p ELSE 0 END - x.p * y.p)), 6) + 0.0 AS h
FROM a p JOIN a r USING (row_id) JOIN z x USING (row_id) JOIN z y USING (row_id) WHERE x.k <= y.k AND y.k < 3 GROUP BY ALL"""


@q(_BLOCKS)
def softmax_hessian_block(spark, sf, d=8, classes=3):
    """Blocks of three classes, from the Gram matrix of the root rows."""
    h = scan(design.embeddings_multi(spark, sf).head(d), Softmax(10), hessian_at=w_soft(d)).gram
    rows = [(k, m, i, j, float(h[k * d + i, m * d + j])) for k in range(classes) for m in range(k, classes) for i in range(d) for j in range(d)]
    return rounded(spark.createDataFrame(rows, "k long, l long, i long, j long, h double"), "h")


@q(f"{_softmax(64)} SELECT row_id AS vec_id, arg_max(k, round(t, 9)) AS pred FROM z GROUP BY row_id")
def softmax_argmax(spark, sf):
    rows = design.embeddings_multi(spark, sf).df
    w = w_soft(64)
    scores = F.array(*[F.struct(F.round(X.dot(F.col("x"), X.weights(w[k * 64 : k * 64 + 64])), 9).alias("t"), F.lit(k).cast("long").alias("k")) for k in range(10)])
    return rows.select(F.col("row_id").alias("vec_id"), F.array_max(scores)["k"].alias("pred"))


_NUM = """WITH b AS (SELECT l_quantity / 50.0 AS x0, l_discount * 10.0 AS x1, l_tax * 10.0 AS x2, p_size / 50.0 AS x3, p_retailprice / 1000.0 AS x4, l_extendedprice / 50000.0 AS x5, l_orderkey FROM lineitem JOIN part ON l_partkey = p_partkey),
c AS (SELECT *, x0 * 1.5 - x1 * 0.5 + x2 * 0.25 + x3 - x4 * 0.75 + x5 * 2.0 + ({u} - 0.5) AS y, [x0, x1, x2, x3, x4, x5] AS x, row_number() OVER () AS id FROM b),
a AS (SELECT id, y, r.i, x[r.i + 1]::DOUBLE AS v FROM c, (SELECT unnest(range(0, 6)) AS i) r)"""


def _numeric_sql():
    from ..functions.hashing import uniform_sql

    return _NUM.format(u=uniform_sql("l_orderkey", 8, 1))


@q(f"{_numeric_sql()}, f AS (SELECT id, y, sum(v * {W_SQL}) AS t FROM a GROUP BY id, y) SELECT i, round(avg(v * (t - f.y)) + 0.001 * {W_SQL}, 6) + 0.0 AS g FROM a JOIN f USING (id) GROUP BY i")
def ridge_gradient(spark, sf):
    return _vector(spark, scan(design.numeric(spark, sf), Ridge(1e-3), (), [w_fix(6)]).gradients[0])


@q(f"{_numeric_sql()}, n AS (SELECT i, avg(v * y) AS rhs FROM a GROUP BY i) SELECT p.i, r.i AS j, round(avg(p.v * r.v) + CASE WHEN p.i = r.i THEN 0.001 ELSE 0 END, 5) + 0.0 AS h, round(n.rhs, 6) + 0.0 AS rhs FROM a p JOIN a r USING (id) JOIN n ON n.i = p.i GROUP BY p.i, r.i, n.rhs")
def ridge_normal_eq(spark, sf):
    d = design.numeric(spark, sf)
    s = scan(d, Ridge(1e-3), (), [[0.0] * 6], [0.0] * 6)
    rows = [(i, j, float(s.gram[i, j]), float(-s.gradients[0][i])) for i in range(6) for j in range(6)]
    return rounded(spark.createDataFrame(rows, "i long, j long, h double, rhs double"), "rhs").withColumn("h", F.round("h", 5) + 0.0)


@q(f"{_numeric_sql()} SELECT p.i, r.i AS j, round(avg(p.v * r.v), 5) + 0.0 AS h FROM a p JOIN a r USING (id) WHERE p.i <= r.i GROUP BY ALL")
def linreg_gram(spark, sf):
    return _upper(spark, scan(design.numeric(spark, sf), Ridge(0.0), hessian_at=[0.0] * 6).gram, 5)


@q(f"{_numeric_sql()} SELECT round(regr_slope(y, x0), 6) + 0.0 AS slope, round(regr_intercept(y, x0), 6) + 0.0 AS intercept FROM c")
def linreg_1d(spark, sf):
    x = design.numeric(spark, sf).df.select("y", F.col("x")[0].alias("x"))
    return rounded(x.agg(F.regr_slope("y", "x").alias("slope"), F.regr_intercept("y", "x").alias("intercept")), "slope", "intercept")


@q(f"{margin()} SELECT i, round(avg(v * -m.y * greatest(0, 1 - m.y * t)) + {LAM} * {W_SQL}, 6) + 0.0 AS g FROM a JOIN m USING (row_id) GROUP BY i")
def svm_gradient(spark, sf):
    return _vector(spark, scan(design.embeddings(spark, sf), SquaredHinge(LAM), (), [w_fix(64)]).gradients[0])


@q(f"{margin(16)} SELECT p.i, r.i AS j, round(avg(CASE WHEN m.y * t < 1 THEN p.v * r.v ELSE 0 END) + CASE WHEN p.i = r.i THEN {LAM} ELSE 0 END, 6) + 0.0 AS h FROM a p JOIN a r USING (row_id) JOIN m USING (row_id) WHERE p.i <= r.i GROUP BY p.i, r.i")
def svm_active_hessian(spark, sf, d=16):
    return _upper(spark, scan(design.embeddings(spark, sf).head(d), SquaredHinge(LAM), hessian_at=w_fix(d)).gram)


# ------------------------------------------------------------------ linear program and lasso
_LP = """WITH s AS (SELECT l_suppkey AS row_id, p_brand, sum(l_quantity) AS qty FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL),
b AS (SELECT 'Brand#' || (k + 1) AS brand, k AS i FROM range(0, 25) r(k)),
g AS (SELECT d.row_id, b.i, coalesce(s.qty, 0) AS q FROM (SELECT DISTINCT row_id FROM s) d CROSS JOIN b LEFT JOIN s ON s.row_id = d.row_id AND s.p_brand = b.brand),
v AS (SELECT row_id, i, q / sum(q) OVER (PARTITION BY row_id) AS v, 1.0 AS rhs FROM g),
box AS (SELECT 1000000000 + k AS row_id, b.i, CASE WHEN b.i = k THEN 1.0 WHEN b.i + 25 = k THEN -1.0 ELSE 0.0 END AS v, CASE WHEN k < 25 THEN 3.0 ELSE 0.0 END AS rhs FROM range(0, 50) r(k), b),
a AS (SELECT row_id::BIGINT AS row_id, i, v::DOUBLE AS v, rhs::DOUBLE AS rhs FROM v UNION ALL SELECT row_id::BIGINT, i, v::DOUBLE, rhs::DOUBLE FROM box),
t AS (SELECT row_id, rhs, rhs - sum(v * 0.3) AS slack FROM a GROUP BY row_id, rhs),
c AS (SELECT b.i, -avg(p_retailprice) / 1000.0 AS c FROM part JOIN b ON p_brand = brand GROUP BY b.i)"""


@q(f"{_LP} SELECT row_id, round(slack, 6) + 0.0 AS slack FROM t")
def lp_slack(spark, sf):
    d, _ = design.brand_program(spark, sf)
    return rounded(d.df.select("row_id", (F.col("y") - X.dot(F.col("x"), X.weights([0.3] * 25))).alias("slack")), "slack")


@q(f"{_LP} SELECT row_id, i, round(v, 6) + 0.0 AS a FROM v WHERE v > 0")
def supplier_brand_matrix(spark, sf):
    d, _ = design.brand_program(spark, sf)
    return rounded(d.df.where("row_id < 1000000000").select("row_id", F.posexplode("x").alias("i", "a")).where("a > 0"), "a")


@q(f"{_LP} SELECT min(slack) > 0 AS feasible, count(*) AS n_rows FROM t")
def lp_feasible(spark, sf):
    d, _ = design.brand_program(spark, sf)
    slack = F.col("y") - X.dot(F.col("x"), X.weights([0.3] * 25))
    return d.df.agg((F.min(slack) > 0).alias("feasible"), F.count(F.lit(1)).alias("n_rows"))


@q(f"{_LP} SELECT a.i, round(5.0 * any_value(c.c) + sum(v / slack), 5) + 0.0 AS g FROM a JOIN t USING (row_id) JOIN c ON c.i = a.i GROUP BY a.i")
def lp_gradient(spark, sf):
    from ..plans.problems import LinearProgram

    d, c = design.brand_program(spark, sf)
    g = scan(d, LinearProgram(c, 5.0), (), [[0.3] * 25]).gradients[0]
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(g)], "i long, g double").withColumn("g", F.round("g", 5) + 0.0)


@q(f"{_LP} SELECT p.i, r.i AS j, round(sum(p.v * r.v / (slack * slack)), 5) + 0.0 AS h FROM a p JOIN a r USING (row_id) JOIN t USING (row_id) WHERE p.i <= r.i GROUP BY ALL")
def lp_hessian(spark, sf):
    from ..plans.problems import LinearProgram

    d, c = design.brand_program(spark, sf)
    h = scan(d, LinearProgram(c, 5.0), hessian_at=[0.3] * 25).gram
    rows = [(i, j, float(h[i, j])) for i in range(25) for j in range(i, 25)]
    return spark.createDataFrame(rows, "i long, j long, h double").withColumn("h", F.round("h", 5) + 0.0)


def lasso_parts(spark, sf):
    """(dictionary, target, bound): vector 0 against all others; bound 0.3 of the largest
    inner product."""
    d = design.embeddings(spark, sf)
    y = d.df.where("row_id = 0").select("x").head()[0]
    columns = design.DesignMatrix(d.df.where("row_id <> 0"), 64)
    top = columns.df.agg(F.max(F.abs(X.dot(F.col("x"), X.weights(y))))).head()[0]
    return columns, y, 0.3 * top


_LASSO = f"""{emb()}, yv AS (SELECT i, v FROM a WHERE row_id = 0), c AS (SELECT row_id, i, v FROM a WHERE row_id <> 0),
k AS (SELECT row_id, sum(c.v * yv.v) AS p FROM c JOIN yv USING (i) GROUP BY row_id), lam AS (SELECT 0.3 * max(abs(p)) AS lam FROM k),
t AS (SELECT row_id, 0.1 * p AS t, lam FROM k, lam)"""


@q(f"{_LASSO} SELECT c.i, round(2.0 * (0.1 - 1) * any_value(yv.v) + sum(c.v * (1 / (lam - t) - 1 / (lam + t))), 5) + 0.0 AS g FROM c JOIN t USING (row_id) JOIN yv ON yv.i = c.i GROUP BY c.i")
def lasso_dual_gradient(spark, sf):
    from ..plans.problems import LassoDual

    d, y, bound = lasso_parts(spark, sf)
    g = scan(d, LassoDual(y, bound, 2.0), (), [0.1 * np.array(y)]).gradients[0]
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(g)], "i long, g double").withColumn("g", F.round("g", 5) + 0.0)


@q(f"{_LASSO} SELECT p.i, r.i AS j, round(CASE WHEN p.i = r.i THEN 2.0 ELSE 0.0 END + sum(p.v * r.v * (1 / ((lam - t) * (lam - t)) + 1 / ((lam + t) * (lam + t)))), 4) + 0.0 AS h FROM c p JOIN c r USING (row_id) JOIN t USING (row_id) WHERE p.i <= r.i AND r.i < 16 GROUP BY p.i, r.i")
def lasso_dual_hessian(spark, sf, upto=16):
    from ..plans.problems import LassoDual

    d, y, bound = lasso_parts(spark, sf)
    h = scan(d, LassoDual(y, bound, 2.0), hessian_at=0.1 * np.array(y)).gram
    rows = [(i, j, float(h[i, j])) for i in range(upto) for j in range(i, upto)]
    return spark.createDataFrame(rows, "i long, j long, h double").withColumn("h", F.round("h", 4) + 0.0)


@q(f"{_LASSO} SELECT round(max(abs(t)), 6) + 0.0 AS max_abs_corr, round(any_value(lam), 6) + 0.0 AS bound, sum((abs(t) >= 0.5 * lam / 3)::INT)::BIGINT AS n_near FROM t")
def lasso_kkt(spark, sf):
    d, y, bound = lasso_parts(spark, sf)
    p = 0.1 * X.dot(F.col("x"), X.weights(y))
    return rounded(d.df.agg(F.max(F.abs(p)).alias("max_abs_corr"), F.lit(float(bound)).alias("bound"), F.count_if(F.abs(p) >= 0.5 * bound / 3).alias("n_near")), "max_abs_corr", "bound")


# ------------------------------------------------------------------ sketches
SK = sketch.BlockSketch(10, 2, 16, 5)
LIVE = [k for k in range(SK.blocks) if k not in (3, 7)]


def _sk(d):
    """The sketch with as many buckets a block as features."""
    return sketch.BlockSketch(SK.n, SK.spare, d, SK.seed)



def _hashed(s: sketch.BlockSketch, blocks, ids="row_id", source="e") -> str:
    each = " UNION ALL ".join(f"SELECT {ids} AS row_id, {k} AS block, {hash_sql(ids, s.coef(k))} AS h FROM {source}" for k in blocks)
    return f"hs AS (SELECT row_id, block::BIGINT AS block, ((h // 2) % {s.width})::BIGINT AS bucket, (1 - 2 * (h % 2))::BIGINT AS sign FROM ({each}))"


_ALL = _hashed(SK, range(SK.blocks))
_USED = _hashed(SK, [k for k in range(SK.blocks) if k not in (3, 7)])
_APPLIED = f"{emb(16)}, {_USED}, sk AS (SELECT block, bucket, i, sum(sign * v) AS v FROM a JOIN hs USING (row_id) GROUP BY ALL)"


@q(f"{emb(1)}, {_ALL} SELECT row_id AS id, block AS blk, bucket, sign FROM hs")
def sketch_hash_bucket_sign(spark, sf):
    return SK.placed(design.embeddings(spark, sf).df.select("row_id")).select(F.col("row_id").alias("id"), F.col("block").alias("blk"), "bucket", "sign")


@q(f"{emb(1)}, {_ALL} SELECT block AS blk, count(DISTINCT bucket) AS n_used, max(n) AS fullest FROM (SELECT block, bucket, count(*) AS n FROM hs GROUP BY ALL) GROUP BY block")
def sketch_bucket_occupancy(spark, sf):
    n = SK.placed(design.embeddings(spark, sf).df.select("row_id")).groupBy("block", "bucket").count()
    return n.groupBy(F.col("block").alias("blk")).agg(F.countDistinct("bucket").alias("n_used"), F.max("count").alias("fullest"))


@q(f"{_APPLIED} SELECT block AS blk, bucket, i, round(v, 6) + 0.0 AS v FROM sk WHERE abs(v) > 1e-9")
def sketch_apply(spark, sf, d=16):
    out = _sk(d).apply_sql(design.embeddings(spark, sf).head(d).df, LIVE)
    return rounded(out.where("abs(v) > 1e-9").withColumnRenamed("block", "blk"), "v")


@q(QUERIES["sketch_apply"][1])
def sketch_apply_arrow(spark, sf, d=16):
    out = _sk(d).apply_arrow(design.embeddings(spark, sf).head(d).df, d, LIVE, group=4)

    def unpack(batches):
        import pyarrow as pa

        for b in batches:
            for blk, bucket, raw in zip(*(b.column(c).to_pylist() for c in b.schema.names)):
                v = np.frombuffer(raw, np.float64)
                yield pa.record_batch([pa.array([blk] * len(v), pa.int32()), pa.array([bucket] * len(v), pa.int32()), pa.array(range(len(v)), pa.int32()), pa.array(v)], names=["blk", "bucket", "i", "v"])

    return rounded(out.mapInArrow(unpack, "blk int, bucket int, i int, v double").where("abs(v) > 1e-9"), "v")


@q(f"{_APPLIED}, p AS (SELECT block, bucket, sum(v * {W_SQL}) AS p FROM sk GROUP BY ALL), t AS (SELECT sum(t * t) AS n FROM (SELECT sum(v * {W_SQL}) AS t FROM a GROUP BY row_id)) SELECT block AS blk, round(sqrt(sum(p * p) / any_value(n)), 6) + 0.0 AS ratio FROM p, t GROUP BY block")
def sketch_norm_ratio(spark, sf, features=16):
    d = design.embeddings(spark, sf).head(features)
    w = w_fix(features)
    full = d.df.agg(F.sum(F.pow(X.dot(F.col("x"), X.weights(w)), 2))).head()[0]
    weight = spark.createDataFrame([(i, x) for i, x in enumerate(w)], "i int, w double")
    p = _sk(features).apply_sql(d.df, LIVE).join(F.broadcast(weight), "i").groupBy("block", "bucket").agg(F.sum(F.col("v") * F.col("w")).alias("p"))
    return rounded(p.groupBy(F.col("block").alias("blk")).agg(F.sqrt(F.sum(F.col("p") * F.col("p")) / full).alias("ratio")), "ratio")


_GRAM = f"{_APPLIED} SELECT p.i, r.i AS j, round(sum(p.v * r.v) / 10, 6) + 0.0 AS h FROM sk p JOIN sk r USING (block, bucket) WHERE p.i <= r.i GROUP BY ALL"


@q(_GRAM)
def sketched_gram_entries(spark, sf, d=16):
    return rounded(sketch.gram_sql(_sk(d).apply_sql(design.embeddings(spark, sf).head(d).df, LIVE), 10), "h")


def _tile_arrivals():
    return "((block * 37 + ci * 11 + cj * 5) % 12)"


@q(f"""{emb(16)}, {_ALL}, sk AS (SELECT block, bucket, i, sum(sign * v) AS v FROM a JOIN hs USING (row_id) GROUP BY ALL),
h AS (SELECT block, p.i // 8 AS ci, r.i // 8 AS cj, p.i, r.i AS j, sum(p.v * r.v) AS h FROM sk p JOIN sk r USING (block, bucket) WHERE p.i // 8 <= r.i // 8 GROUP BY ALL),
w AS (SELECT *, rank() OVER (PARTITION BY i, j ORDER BY {_tile_arrivals()}, block) AS r FROM h)
SELECT i, j, round(sum(h) / 10, 6) + 0.0 AS h FROM w WHERE r <= 10 AND i <= j GROUP BY ALL""")
def sketched_gram_tile_survivors(spark, sf, d=16):
    """Every tile keeps the first 10 of its 12 block products to arrive."""
    rows = _sk(d).apply_arrow(design.embeddings(spark, sf).head(d).df, d)
    pairs = [(i, j) for i in range(d // 8) for j in range(i, d // 8)]
    grid = spark.range(12).select(F.col("id").cast("int").alias("block")).crossJoin(spark.createDataFrame(pairs, "ci int, cj int"))
    tiles = sketch.gram_tiles(rows, d, 8, 10, grid.withColumn("t", F.expr(_tile_arrivals())))
    return _upper(spark, sketch.assemble(tiles.collect(), d, 8, 10))


@q(f"{emb(16)} SELECT p.i, r.i AS j, round(sum(p.v * r.v), 6) + 0.0 AS h FROM a p JOIN a r USING (row_id) WHERE p.i <= r.i GROUP BY ALL")
def gram_long_join(spark, sf, d=16):
    return rounded(sketch.gram_long(design.embeddings(spark, sf).head(d).df), "h")


@q(QUERIES["gram_long_join"][1])
def gram_exact_arrow(spark, sf, d=16):
    return _upper(spark, sketch.gram_exact(design.embeddings(spark, sf).head(d).df, d))


@q(f"""{_APPLIED}, s AS (SELECT p.i, r.i AS j, sum(p.v * r.v) / 10 AS h FROM sk p JOIN sk r USING (block, bucket) GROUP BY ALL),
x AS (SELECT p.i, r.i AS j, sum(p.v * r.v) AS h FROM a p JOIN a r USING (row_id) GROUP BY ALL)
SELECT round(sqrt(sum((s.h - x.h) * (s.h - x.h)) / sum(x.h * x.h)), 6) + 0.0 AS rel_err FROM s JOIN x USING (i, j)""")
def gram_error_frobenius(spark, sf, features=16):
    d = design.embeddings(spark, sf).head(features)
    a = sketch.gram_driver(_sk(features).apply_arrow(d.df, features, LIVE), features, 10)
    b = sketch.gram_exact(d.df, features)
    return rounded(spark.createDataFrame([(float(np.linalg.norm(a - b) / np.linalg.norm(b)),)], "rel_err double"), "rel_err")


_JL = sketch.BlockSketch(4, 0, 40, 9)


@q(f"""{emb(8)}, {_hashed(_JL, range(4))}, sk AS (SELECT block, bucket, i, sum(sign * v) / 2.0 AS v FROM a JOIN hs USING (row_id) GROUP BY ALL)
SELECT p.i, r.i AS j, round(sum(p.v * r.v), 6) + 0.0 AS h FROM sk p JOIN sk r USING (block, bucket) WHERE p.i <= r.i GROUP BY ALL""")
def sketch_sparse_jl(spark, sf, d=8):
    return rounded(sketch.gram_sql(sketch.sparse_jl(design.embeddings(spark, sf).head(d).df, 20 * d, 4, 9), 1), "h")


def _sampled_sql():
    from ..functions.hashing import uniform_sql

    return uniform_sql("row_id", 53)


@q(f"{emb(8)}, s AS (SELECT a.* FROM a WHERE {_sampled_sql()} < 0.5) SELECT p.i, r.i AS j, round(sum(p.v * r.v) / 0.5, 6) + 0.0 AS h FROM s p JOIN s r USING (row_id) WHERE p.i <= r.i GROUP BY ALL")
def sketch_rowsample(spark, sf, d=8):
    return rounded(sketch.gram_long(sketch.row_sample(design.embeddings(spark, sf).head(d).df, 0.5)), "h")


def _other(make):
    def run(spark, sf):
        return _upper(spark, sketch.gram_driver(make(design.embeddings(spark, sf).df), 64, 1))

    return run


q(None, "sketch_gaussian")(_other(lambda df: sketch.gaussian(df, 64, 3200)))
q(None, "sketch_hadamard_block")(_other(lambda df: sketch.hadamard(df, 64, 64, 48)))


# ------------------------------------------------------------------ codes
def _ranked(spark, sf):
    """Embeddings ranked by id, and their number."""
    d = design.embeddings(spark, sf).df
    return coding.ranked(d.select("row_id", "x"), "row_id").select("rank", "row_id", "x"), d.count()


_GRID = f"""{emb()}, k AS (SELECT row_id, row_number() OVER (ORDER BY row_id) - 1 AS rank FROM e), z AS (SELECT greatest(1, ceil(count(*) / 9.0))::BIGINT AS size FROM e),
g AS (SELECT row_id, rank // (size * 3) AS r, rank // size % 3 AS c, rank % size AS offset_ FROM k, z)"""


def _code(spark, sf):
    rows, n = _ranked(spark, sf)
    return coding.ProductCode.encode(rows, n, 3)


def _parity(where, keep, upto=8):
    def run(spark, sf):
        long = _code(spark, sf).blocks.where(where).select("r", "c", F.col("offset").alias("offset_"), F.posexplode("x").alias("i", "v"))
        return rounded(long.where(F.col("i") < upto).select(*keep, "offset_", "i", "v"), "v")

    return run


q(f"{_GRID} SELECT r, offset_, i, round(sum(v), 6) + 0.0 AS v FROM g JOIN a USING (row_id) WHERE i < 8 GROUP BY ALL", "code_row_parity")(_parity("c = 3 AND r < 3", ["r"]))
q(f"{_GRID} SELECT c, offset_, i, round(sum(v), 6) + 0.0 AS v FROM g JOIN a USING (row_id) WHERE i < 8 GROUP BY ALL", "code_col_parity")(_parity("r = 3 AND c < 3", ["c"]))
q(f"{_GRID} SELECT offset_, i, round(sum(v), 6) + 0.0 AS v FROM g JOIN a USING (row_id) WHERE i < 8 GROUP BY ALL", "code_corner_parity")(_parity("r = 3 AND c = 3", []))


@q(f"{_GRID} SELECT CASE WHEN r.k = 0 THEN 'data' WHEN r.k = 1 THEN 'row' WHEN r.k = 2 THEN 'col' ELSE 'corner' END AS kind, count(DISTINCT CASE WHEN r.k = 0 THEN row_id WHEN r.k = 1 THEN r * 1000000 + offset_ WHEN r.k = 2 THEN c * 1000000 + offset_ ELSE offset_ END) AS n FROM g, range(0, 4) r(k) GROUP BY ALL")
def coded_union(spark, sf):
    kind = F.when((F.col("r") < 3) & (F.col("c") < 3), "data").when(F.col("r") < 3, "row").when(F.col("c") < 3, "col").otherwise("corner")
    return _code(spark, sf).blocks.groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("n"))


@q(f"{_GRID}, m AS (SELECT row_id, sum(v * {W_SQL}) AS t FROM a GROUP BY row_id) SELECT r, offset_, round(sum(t), 6) + 0.0 AS y FROM g JOIN m USING (row_id) GROUP BY ALL")
def coded_matvec_parity(spark, sf):
    """Products of the row parities: sums of the data blocks' products."""
    return rounded(_code(spark, sf).products(w_fix(64)).where("c = 3 AND r < 3").select("r", F.col("offset").alias("offset_"), "y"), "y")


ERASED = {(0, 0), (0, 1), (1, 1), (2, 3), (3, 3)}


@q(QUERIES["margin_dot"][1])
def coded_matvec_decoded(spark, sf):
    """Five of sixteen blocks are lost and peeled back; equal to the plain product."""
    code = _code(spark, sf)
    return rounded(code.decode(code.products(w_fix(64)), ERASED).select(F.col("row_id").alias("vec_id"), F.col("y").alias("alpha")), "alpha")


_LOST = " UNION ALL ".join(f"SELECT {r} AS r, {c} AS c" for r, c in sorted(ERASED))


@q(f"WITH x AS ({_LOST}) SELECT 'row' AS line, r::BIGINT AS k FROM x GROUP BY r HAVING count(*) = 1 UNION ALL SELECT 'col', c::BIGINT FROM x GROUP BY c HAVING count(*) = 1")
def peel_candidates(spark, sf):
    """Lines with exactly one missing block."""
    x = spark.createDataFrame(sorted(ERASED), "r long, c long")
    one = lambda name, c: x.groupBy(c).count().where("count = 1").select(F.lit(name).alias("line"), F.col(c).alias("k"))
    return one("row", "r").unionByName(one("col", "c"))


@q(f"WITH x AS ({_LOST}), g AS (SELECT o_orderkey // 4 % 4 AS r, o_orderkey % 4 AS c FROM orders) SELECT r, c, count(*) AS n FROM g ANTI JOIN x USING (r, c) GROUP BY r, c")
def blocks_surviving_anti(spark, sf):
    """Orders dealt to a grid of 16 blocks: the rows of each block that isn't lost."""
    g = tables.table(spark, sf, "orders", "o_orderkey").select(F.expr("o_orderkey div 4 % 4").alias("r"), (F.col("o_orderkey") % 4).alias("c"))
    return g.join(F.broadcast(spark.createDataFrame(sorted(ERASED), "r long, c long")), ["r", "c"], "left_anti").groupBy("r", "c").agg(F.count(F.lit(1)).alias("n"))


@q(f"{margin()}, k AS (SELECT row_id, t, row_number() OVER (ORDER BY row_id) - 1 AS rank FROM m), h AS (SELECT ceil(count(*) / 2.0)::BIGINT AS half FROM m) SELECT rank % half AS offset_, round(t, 6) + 0.0 AS alpha FROM k, h WHERE rank < half")
def coded_single_parity(spark, sf):
    """Two halves and their sum: the first half's product from the other two results.  A last
    half that is a row short counts as ending in zeros."""
    rows, n = _ranked(spark, sf)
    half = max(1, -(-n // 2))
    part = rows.select(F.floor(F.col("rank") / half).cast("int").alias("part"), (F.col("rank") % half).alias("offset"), F.posexplode("x").alias("i", "v"))
    coded = part.unionByName(part.groupBy("offset", "i").agg(F.sum("v").alias("v")).withColumn("part", F.lit(2)))
    w = spark.createDataFrame([(i, x) for i, x in enumerate(w_fix(64))], "i int, w double")
    y = coded.join(F.broadcast(w), "i").where("part <> 0").groupBy("part", "offset").agg(F.sum(F.col("v") * F.col("w")).alias("y"))
    return rounded(y.groupBy(F.col("offset").alias("offset_")).agg(F.sum(F.when(F.col("part") == 2, F.col("y")).otherwise(-F.col("y"))).alias("alpha")), "alpha")


@q(f"{margin()}, k AS (SELECT row_id, t, row_number() OVER (ORDER BY row_id) - 1 AS rank FROM m), h AS (SELECT ceil(count(*) / 4.0)::BIGINT AS n FROM m), z AS (SELECT p AS part, o AS offset_ FROM h, range(0, 4) a(p), unnest(range(0, n)) b(o)) SELECT z.part, z.offset_, round(coalesce(t, 0), 6) + 0.0 AS alpha FROM z CROSS JOIN h LEFT JOIN k ON k.rank = z.part * h.n + z.offset_")
def mds_decode(spark, sf):
    """Any four of six coded parts give the product; here parts 1, 3, 4 and 5.  Rows missing
    from the last part are zeros."""
    rows, n = _ranked(spark, sf)
    size = max(1, -(-n // 4))
    part = rows.select(F.floor(F.col("rank") / size).cast("int").alias("part"), (F.col("rank") % size).alias("offset"), F.posexplode("x").alias("i", "v"))
    w = spark.createDataFrame([(i, x) for i, x in enumerate(w_fix(64))], "i int, w double")
    y = coding.mds_encode(part, 4, 2).join(F.broadcast(w), "i").groupBy("part", "offset").agg(F.sum(F.col("v") * F.col("w")).alias("y"))
    out = coding.mds_decode(y.where("part IN (1, 3, 4, 5)"), 4, 2, [1, 3, 4, 5])
    return rounded(out.select("part", F.col("offset").alias("offset_"), F.col("y").alias("alpha")), "alpha")


def _shard_gradients(spark, sf):
    """(shard, i, g): gradient sums of four shards by row id."""
    rows = design.embeddings(spark, sf).df.withColumn("t", X.dot(F.col("x"), X.weights(w_fix(64))))
    beta = -F.col("y") * X.sigmoid(-F.col("y") * F.col("t"))
    long = rows.select((F.col("row_id") % 4).cast("int").alias("shard"), beta.alias("b"), F.posexplode("x").alias("i", "v"))
    return long.groupBy("shard", "i").agg(F.sum(F.col("v") * F.col("b")).alias("g"))


@q(f"{margin()} SELECT i, round(sum(v * -m.y / (1 + exp(m.y * t))), 6) + 0.0 AS g FROM a JOIN m USING (row_id) GROUP BY i")
def gradient_code_decode(spark, sf):
    """Four workers with two shards each; worker 2 is lost."""
    return rounded(coding.coded_sum(_shard_gradients(spark, sf), coding.cyclic_code(4, 1), [0, 1, 3]), "g")


@q("WITH s AS (SELECT o_orderkey % 4 AS p, count(*) AS n FROM orders GROUP BY p) SELECT w AS worker, p AS shard, 1.0::DOUBLE AS coef, n FROM range(0, 4) a(w) JOIN s ON w // 2 = p // 2")
def gradient_code_placement(spark, sf):
    """Which worker holds which of four shards of the orders, by what coefficient, and how many rows."""
    shards = tables.table(spark, sf, "orders", "o_orderkey").groupBy((F.col("o_orderkey") % 4).alias("shard")).agg(F.count(F.lit(1)).alias("n"))
    return shards.join(F.broadcast(coding.placement(spark, coding.fractional_code(4, 1))), "shard").select("worker", "shard", "coef", "n")


@q(f"{emb()} SELECT label, i, round(sum(v), 6) + 0.0 AS s FROM a GROUP BY ALL")
def vector_sum(spark, sf):
    e = tables.table(spark, sf, "embeddings", "label", "embedding").withColumn("embedding", F.col("embedding").cast("array<double>"))
    return rounded(sum_arrays(e, "label", "embedding"), "s")


# ------------------------------------------------------------------ all features
def _wide(name):
    """The SQL of a query over the first features, over all 64 (and all classes), with the
    sketch as much larger."""
    sql = QUERIES[name][1]
    for cut, whole in (("range(0, 16)", "range(0, 64)"), ("range(0, 8)", "range(0, 64)"), ("(h // 2) % 16)", "(h // 2) % 64)"), ("(h // 2) % 40)", "(h // 2) % 320)"), (" AND r.i < 16", ""), (" AND y.k < 3", ""), (" WHERE i < 8", "")):
        sql = sql.replace(cut, whole)
    return sql


for _f in (logistic_hessian, svm_active_hessian, lasso_dual_hessian, sketch_apply, sketch_apply_arrow, sketch_norm_ratio, sketched_gram_entries, sketched_gram_tile_survivors, gram_long_join, gram_exact_arrow, gram_error_frobenius, sketch_sparse_jl, sketch_rowsample):
    q(_wide(_f.__name__), f"{_f.__name__}_whole")(lambda spark, sf, _f=_f: _f(spark, sf, 64))
q(_wide("softmax_hessian_block"), "softmax_hessian_block_whole")(lambda spark, sf: softmax_hessian_block(spark, sf, 64, 10))
for _name, _where, _keep in (("row", "c = 3 AND r < 3", ["r"]), ("col", "r = 3 AND c < 3", ["c"]), ("corner", "r = 3 AND c = 3", [])):
    q(_wide(f"code_{_name}_parity"), f"code_{_name}_parity_whole")(_parity(_where, _keep, 64))
