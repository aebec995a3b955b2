"""Encoders, joins, windows, set operations and streaming twins that the methods use."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import columns as X
from ..functions.hashing import coefficients, hash_col, hash_sql, uniform_col, uniform_sql
from ..sources import design, tables
from ..streaming import windows
from .base import Registry, emb, rounded

QUERIES = Registry()
q = QUERIES.add
t = tables.table


@q("SELECT l_orderkey, l_linenumber::BIGINT AS l_linenumber, round(l_extendedprice * (1 - l_discount), 6) + 0.0 AS net FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")
def scan_lineitem_projection(spark, sf):
    rows = t(spark, sf, "lineitem").where((F.col("l_quantity") > 45) & (F.col("l_returnflag") == "R"))
    return rounded(rows.select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net")), "net")


@q("""SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice IS NULL THEN 'none' ELSE 'low' END AS band, coalesce(nullif(o_orderstatus, 'P'), '?') AS status FROM orders
WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1000 AND 300000 AND o_orderstatus LIKE '%' AND o_orderstatus IS DISTINCT FROM 'X'""")
def predicate_mix(spark, sf):
    o = t(spark, sf, "orders")
    o = o.where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_totalprice").between(1000, 300000) & F.col("o_orderstatus").like("%") & ~F.col("o_orderstatus").eqNullSafe("X"))
    band = F.when(F.col("o_totalprice") > 200000, "high").when(F.col("o_totalprice").isNull(), "none").otherwise("low")
    return o.select("o_orderkey", band.alias("band"), F.coalesce(F.nullif("o_orderstatus", F.lit("P")), F.lit("?")).alias("status"))


@q("SELECT count(*) AS n_rows, (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)) AS n_short, (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice FROM lineitem)) AS n_full FROM lineitem")
def row_id_collisions(spark, sf):
    """How many rows two candidate keys tell apart; the sketch needs unique ids."""
    rows = t(spark, sf, "lineitem", *design.LINE_KEY)
    return rows.agg(F.count(F.lit(1)).alias("n_rows"), F.countDistinct("l_orderkey", "l_linenumber").alias("n_short"), F.countDistinct(*design.LINE_KEY).alias("n_full"))


@q("SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber::BIGINT AS l_linenumber, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS ordinal FROM lineitem")
def row_id_assignment(spark, sf):
    """Ordinals inside an order: an id without a global sort."""
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")
    return t(spark, sf, "lineitem", *design.LINE_KEY).select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.row_number().over(w).alias("ordinal"))


_STAR = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"


@q(f"SELECT n_regionkey::BIGINT AS n_regionkey, c_mktsegment, count(*) AS n, round(avg(p_retailprice), 6) + 0.0 AS price, round(sum(l_quantity), 6) + 0.0 AS qty FROM {_STAR} GROUP BY ALL")
def features_star_join(spark, sf):
    out = design.star(spark, sf).groupBy("n_regionkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.avg("p_retailprice").alias("price"), F.sum("l_quantity").alias("qty"))
    return rounded(out, "price", "qty")


@q(f"""WITH s AS (SELECT * FROM {_STAR}), f AS (
SELECT unnest([(l_returnflag = 'N')::INT, (l_returnflag = 'R')::INT, (l_linestatus = 'O')::INT, (o_orderstatus = 'O')::INT, (o_orderstatus = 'P')::INT, (c_mktsegment = 'BUILDING')::INT]) AS v, unnest(range(0, 6)) AS i FROM s)
SELECT i, sum(v)::DOUBLE AS s FROM f GROUP BY i""")
def encode_onehot(spark, sf):
    """Column sums of one-hot factors (the first six of them here)."""
    rows = design.star(spark, sf)
    pick = lambda name, levels: design.one_hot(F.col(name), levels)
    cols = pick("l_returnflag", ["A", "N", "R"]) + pick("l_linestatus", ["F", "O"]) + pick("o_orderstatus", ["F", "O", "P"]) + pick("c_mktsegment", ["AUTOMOBILE", "BUILDING"])
    return rows.select(F.posexplode(F.array(*cols)).alias("i", "v")).groupBy("i").agg(F.sum("v").alias("s"))


@q("""WITH m AS (SELECT avg(l_quantity) AS a, stddev_pop(l_quantity) AS b, avg(l_extendedprice) AS c, stddev_pop(l_extendedprice) AS d FROM lineitem)
SELECT l_returnflag, round(avg((l_quantity - a) / b), 6) + 0.0 AS qty, round(avg((l_extendedprice - c) / d), 6) + 0.0 AS price FROM lineitem, m GROUP BY l_returnflag""")
def encode_standardized(spark, sf):
    rows = t(spark, sf, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice")
    m = rows.agg(*[f(c).alias(f"{n}_{c}") for c in ("l_quantity", "l_extendedprice") for n, f in (("m", F.avg), ("s", F.stddev_pop))])
    z = lambda c: F.avg((F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}"))
    return rounded(rows.crossJoin(F.broadcast(m)).groupBy("l_returnflag").agg(z("l_quantity").alias("qty"), z("l_extendedprice").alias("price")), "qty", "price")


@q("SELECT * FROM (VALUES (1.0::DOUBLE, 1::BIGINT, 0.5::DOUBLE), (1.0, 3, 2.0), (-1.0, 2, -1.25)) v(y, i, v)")
def parse_sparse_text(spark, sf):
    lines = spark.createDataFrame([("1 1:0.5 3:2",), (" -1  2:-1.25 ",)], "value string")
    return tables.parse_sparse(lines).select("y", F.explode(F.arrays_zip("idx", "val")).alias("p")).select("y", F.col("p.idx").alias("i"), F.col("p.val").alias("v"))


_GAP = "[\\x20\\x09-\\x0D]+"


@q(f"""WITH w AS (SELECT doc_id, unnest(string_split_regex(lower(text), '{_GAP}')) AS w FROM documents JOIN labels USING (doc_id))
SELECT doc_id, count(*) AS n_terms, count(DISTINCT w) AS n_distinct FROM w WHERE w <> '' GROUP BY doc_id""")
def doc_term_counts(spark, sf):
    """Terms of labelled documents, from whole texts."""
    docs = t(spark, sf, "documents", "doc_id", "text").join(t(spark, sf, "labels", "doc_id"), "doc_id")
    words = F.filter(F.split(F.lower("text"), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    return docs.select("doc_id", words.alias("w")).where("size(w) > 0").select("doc_id", F.size("w").alias("n_terms"), F.size(F.array_distinct("w")).alias("n_distinct"))


@q(None)
def doc_hashed_tf(spark, sf):
    """Hashed term frequencies of unit length (the hash has no SQL twin)."""
    d = design.doc_terms(spark, sf, 50)
    return rounded(d.df.select("row_id", F.posexplode("x").alias("i", "v")).where("v > 0"), "v")


@q("SELECT doc_id, CASE WHEN quality IS NULL THEN 0 WHEN quality = 1 THEN 1 ELSE -1 END::BIGINT AS y FROM documents LEFT JOIN labels USING (doc_id)")
def docs_labels_left(spark, sf):
    y = F.when(F.col("quality").isNull(), 0).when(F.col("quality") == 1, 1).otherwise(-1)
    return t(spark, sf, "documents", "doc_id").join(t(spark, sf, "labels"), "doc_id", "left").select("doc_id", y.alias("y"))


@q("SELECT doc_id, lang FROM documents SEMI JOIN labels USING (doc_id)")
def docs_labeled_semi(spark, sf):
    return t(spark, sf, "documents", "doc_id", "lang").join(t(spark, sf, "labels"), "doc_id", "left_semi")


_PART = hash_sql("vec_id", coefficients(101))


@q(f"SELECT CASE WHEN {_PART} % 4 = 0 THEN 'test' ELSE 'train' END AS split, count(*) AS n FROM embeddings GROUP BY ALL")
def split_counts(spark, sf):
    part = F.when(hash_col(F.col("vec_id"), coefficients(101)) % 4 == 0, "test").otherwise("train")
    return t(spark, sf, "embeddings", "vec_id").groupBy(part.alias("split")).agg(F.count(F.lit(1)).alias("n"))


@q(f"SELECT vec_id FROM embeddings EXCEPT ALL SELECT vec_id FROM embeddings WHERE {_PART} % 4 = 0")
def split_except(spark, sf):
    ids = t(spark, sf, "embeddings", "vec_id")
    return ids.exceptAll(ids.where(hash_col(F.col("vec_id"), coefficients(101)) % 4 == 0))


def _uniform_cols(d):
    return ", ".join(f"round({uniform_sql('o_orderkey', 1, i)} * 2 - 1, 6) + 0.0 AS x{i}" for i in range(d))


@q(f"SELECT o_orderkey AS row_id, {_uniform_cols(4)} FROM orders")
def synth_uniform_features(spark, sf):
    x = design.uniform_features(F.col("o_orderkey"), 4)
    return rounded(t(spark, sf, "orders", "o_orderkey").select(F.col("o_orderkey").alias("row_id"), *[x[i].alias(f"x{i}") for i in range(4)]), "x0", "x1", "x2", "x3")


_W4 = design.planted_weights(4)
_M4 = " + ".join(f"({uniform_sql('o_orderkey', 1, i)} * 2 - 1) * {_W4[i]!r}" for i in range(4)) + f" + {_W4[4]!r}"


@q(f"SELECT CASE WHEN {uniform_sql('o_orderkey', 3, 999)} < 1 / (1 + exp(-({_M4}))) THEN 1.0 ELSE -1.0 END::DOUBLE AS y, count(*) AS n FROM orders GROUP BY ALL")
def synth_planted_labels(spark, sf):
    rows = t(spark, sf, "orders", "o_orderkey").withColumn("x", design.uniform_features(F.col("o_orderkey"), 4))
    margin = X.dot(F.col("x"), X.weights(_W4[:4])) + _W4[4]
    return rows.groupBy(design.planted_label(margin, F.col("o_orderkey")).alias("y")).agg(F.count(F.lit(1)).alias("n"))


@q(f"{emb()} SELECT row_id AS vec_id, round(max(v), 6) + 0.0 AS top, round(sum(v * v), 6) + 0.0 AS sq, count(*) FILTER (v > 0) AS n_pos, round(list_sort(list(v))[2], 6) + 0.0 AS second FROM a GROUP BY row_id")
def array_ops(spark, sf):
    rows = design.embeddings(spark, sf).df
    out = rows.select(F.col("row_id").alias("vec_id"), F.array_max("x").alias("top"), F.aggregate(F.transform("x", lambda v: v * v), F.lit(0.0), lambda a, v: a + v).alias("sq"), F.size(F.filter("x", lambda v: v > 0)).alias("n_pos"), F.sort_array("x")[1].alias("second"))
    return rounded(out, "top", "sq", "second")


@q(f"{emb()} SELECT row_id AS vec_id, round(sum(v * CASE i WHEN 0 THEN 0.5 WHEN 5 THEN -2.0 WHEN 63 THEN 1.5 ELSE 0 END), 6) + 0.0 AS s FROM a GROUP BY row_id")
def sparse_dot_map(spark, sf):
    """A sparse vector as a map against dense rows."""
    m = F.map_from_arrays(F.array(F.lit(0), F.lit(5), F.lit(63)), F.array(F.lit(0.5), F.lit(-2.0), F.lit(1.5)))
    s = F.aggregate(F.map_entries(m), F.lit(0.0), lambda a, e: a + F.get("x", e["key"]) * e["value"])
    return rounded(design.embeddings(spark, sf).df.select(F.col("row_id").alias("vec_id"), s.alias("s")), "s")


@q("SELECT DISTINCT label::BIGINT AS label FROM embeddings WHERE label < 6 INTERSECT SELECT DISTINCT label::BIGINT FROM embeddings WHERE label > 3")
def support_intersect(spark, sf):
    e = t(spark, sf, "embeddings", "label")
    return e.where("label < 6").intersect(e.where("label > 3"))


@q("SELECT coalesce(l_suppkey::VARCHAR, 'all') AS supp, coalesce(p_brand, 'all') AS brand, round(sum(l_quantity), 6) + 0.0 AS qty FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_suppkey < 20 GROUP BY CUBE (l_suppkey, p_brand)")
def load_cube(spark, sf):
    """The cube of the suppliers below 20; ``load_cube_whole`` has all."""
    return _cube(spark, sf, t(spark, sf, "lineitem", "l_partkey", "l_suppkey", "l_quantity").where("l_suppkey < 20"))


def _cube(spark, sf, lines):
    rows = lines.join(t(spark, sf, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    out = rows.cube("l_suppkey", "p_brand").agg(F.sum("l_quantity").alias("qty"))
    return rounded(out.select(F.coalesce(F.col("l_suppkey").cast("string"), F.lit("all")).alias("supp"), F.coalesce("p_brand", F.lit("all")).alias("brand"), "qty"), "qty")


@q(QUERIES["load_cube"][1].replace(" WHERE l_suppkey < 20", ""))
def load_cube_whole(spark, sf):
    return _cube(spark, sf, t(spark, sf, "lineitem", "l_partkey", "l_suppkey", "l_quantity"))


@q("WITH b AS (SELECT * FROM (VALUES (0, 0.0, 10.0), (1, 10.0, 25.0), (2, 25.0, 40.0), (3, 40.0, 1000.0)) v(k, lo, hi)) SELECT k::BIGINT AS k, count(*) AS n, round(avg(l_extendedprice), 6) + 0.0 AS price FROM lineitem JOIN b ON l_quantity >= lo AND l_quantity < hi GROUP BY k")
def bucketize_range_join(spark, sf):
    """A range join with a table of four rows."""
    b = F.broadcast(spark.createDataFrame([(0, 0.0, 10.0), (1, 10.0, 25.0), (2, 25.0, 40.0), (3, 40.0, 1000.0)], "k int, lo double, hi double"))
    rows = t(spark, sf, "lineitem", "l_quantity", "l_extendedprice")
    return rounded(rows.join(b, (F.col("l_quantity") >= F.col("lo")) & (F.col("l_quantity") < F.col("hi"))).groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.avg("l_extendedprice").alias("price")), "price")


# ------------------------------------------------------------------ events
def _events(spark, sf):
    """Events with ``s``, their second: the nearest one, half a second to the even one, as
    DuckDB casts ``epoch(ts)``."""
    return t(spark, sf, "events").withColumn("s", F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).cast("long"))


@q("WITH e AS (SELECT event_id, user_id, epoch(ts)::BIGINT AS s, value FROM events) SELECT a.event_id, count(b.event_id) AS n, round(coalesce(sum(b.value), 0), 6) + 0.0 AS v FROM e a LEFT JOIN e b ON a.user_id = b.user_id AND b.s < a.s AND b.s >= a.s - 86400 GROUP BY a.event_id")
def events_interval_join(spark, sf):
    """Events of the same user in the day before: an equi-join on user and day bucket with
    the range as a filter."""
    e = _events(spark, sf).select("event_id", "user_id", "s", "value")
    day = F.floor(F.col("s") / 86400)
    left = e.select("event_id", F.col("user_id").alias("u"), "s", F.explode_outer(F.array(day, day - 1)).alias("d"))
    right = e.select("user_id", F.col("s").alias("s2"), F.col("value").alias("v2"), day.alias("day"))
    near = (F.col("u") == F.col("user_id")) & (F.col("d") == F.col("day")) & (F.col("s2") < F.col("s")) & (F.col("s2") >= F.col("s") - 86400)
    out = left.join(right, near, "left").groupBy("event_id").agg(F.count("s2").alias("n"), F.coalesce(F.sum("v2"), F.lit(0.0)).alias("v"))
    return rounded(out, "v")


@q("WITH e AS (SELECT event_id, user_id, epoch(ts)::BIGINT AS s, value FROM events) SELECT event_id, count(*) OVER w AS n, round(sum(value) OVER w, 6) + 0.0 AS v FROM e WINDOW w AS (PARTITION BY user_id ORDER BY s RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW)")
def events_trailing_features(spark, sf):
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-604800, 0)
    return rounded(_events(spark, sf).select("event_id", F.count(F.lit(1)).over(w).alias("n"), F.sum("value").over(w).alias("v")), "v")


@q("SELECT event_type, sum(json_extract(props, '$.k')::BIGINT)::BIGINT AS k, count(*) AS n FROM events GROUP BY event_type")
def events_json_feature(spark, sf):
    return t(spark, sf, "events", "event_type", "props").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"), F.count(F.lit(1)).alias("n"))


@q("SELECT year(l_shipdate) AS y, month(l_shipdate) AS m, isodow(l_shipdate) AS dow, count(*) AS n FROM lineitem GROUP BY ALL")
def date_features(spark, sf):
    d = F.col("l_shipdate")
    dow = F.pmod(F.dayofweek(d) + 5, F.lit(7)) + 1
    return t(spark, sf, "lineitem", "l_shipdate").groupBy(F.year(d).alias("y"), F.month(d).alias("m"), dow.alias("dow")).agg(F.count(F.lit(1)).alias("n"))


def _start(c="window.start"):
    return F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias("start")


@q("SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 6) + 0.0 AS v FROM events GROUP BY ALL")
def events_window_tumbling(spark, sf):
    return rounded(windows.tumbling(windows.timed(t(spark, sf, "events"))).select(_start(), "n", "v"), "v")


@q("WITH e AS (SELECT ts, value, unnest(range(0, 7)) AS k FROM events) SELECT strftime(time_bucket(INTERVAL 1 DAY, ts) - to_days(k::INT), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 6) + 0.0 AS v FROM e GROUP BY ALL")
def events_window_sliding(spark, sf):
    return rounded(windows.sliding(windows.timed(t(spark, sf, "events"))).select(_start(), "n", "v"), "v")


@q("""WITH e AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, value, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 6) + 0.0 AS v FROM s GROUP BY user_id, k""")
def events_window_session(spark, sf):
    return rounded(windows.sessions(windows.timed(t(spark, sf, "events"))).select("user_id", _start("session_window.start"), "n", "v"), "v")


@q("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def events_dedup(spark, sf):
    e = t(spark, sf, "events", "event_id", "event_type")
    return e.unionByName(e).dropDuplicates(["event_id"]).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


_EV = windows.SKETCH


def _event_hash():
    each = " UNION ALL ".join(f"SELECT event_id, ts, value, {k} AS block, {hash_sql('event_id', _EV.coef(k))} AS h FROM events" for k in range(_EV.blocks))
    return f"SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M:%S') AS start, block::BIGINT AS block, ((h // 2) % {_EV.width})::BIGINT AS bucket, round(sum((1 - 2 * (h % 2)) * value), 6) + 0.0 AS v FROM ({each}) GROUP BY ALL"


@q(_event_hash())
def events_sketch_by_day(spark, sf):
    """A sketch for each day; sketches add, so any span of days is a sum of these."""
    return rounded(windows.sketch_by_window(windows.timed(t(spark, sf, "events"))).select(_start(), "block", "bucket", "v"), "v")
