"""Mixing sources to target weights, in DataFrame functions only.

Words of a source form one long stream: documents in the order of (bucket, id), buckets
dealt by hash, with running offsets taken inside buckets and over bucket totals, so that no
window holds more than a bucket.  The stream is cut in blocks of ``block`` words.

A source's target is a number of words, and so a number of slots of one block each.  Output
shards have ``shard_slots`` slots; each draws the sources of its slots independently, by
the share of the sources in all slots, so its counts are multinomial.  The draws of a source
are numbered over all shards.  Those beyond its number of slots are given to the sources
that were drawn too seldom, in order; they are the last draws of their source, about the root
of all slots in number.  So all shards are full, and totals are exact.

Number ``i`` of a source's slots takes, in pass ``i`` div blocks, the block that a keyed
permutation of the block indices gives for the rest: a Feistel network over the least power
of two, walked until it falls on an index (drawn anew for each pass).  A whole pass takes
every block once; the last slot takes only the words that are still missing.

Blocks and documents meet in an equi-join by (source, block), both sides of which have many
small keys, so a hot source is spread evenly.  Sources are ranked, summed and found by
ranges of names, so there may be many.

Edge cases: null and empty texts have size 0 and are taken 0 times; null source is a source
of its own, last in order; sources of size 0 have target 0; an empty table mixes to an
empty table; repeated rows are documents of their own (ties by text); other columns aren't
read by ``mix`` and travel with the text in ``mixed_texts``, where an id occurs once for each
pass that takes words of the document.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import common as C

WEIGHTS = (3.0, 1.0, 2.0)  # fixed values of the contract, repeating over the sources
BLOCK = 256
SHARD_SLOTS = 256
RUN_SLOTS = 1 << 16  # draws that are numbered in one window
BUCKET_ROWS = 50_000  # documents of a source whose offsets are taken in one window, about
RANGES = 4096  # parts of all slots by which a draw finds its source
WALK = 64  # steps of a walk; each falls on an index with a chance of a half at least


# ------------------------------------------------------------------ targets
def _running(df: DataFrame, value: str, out: str, *order) -> DataFrame:
    """Adds the sum of ``value`` over the rows before, in the order that ``df`` (with a
    column ``part`` of consecutive ranges of that order) lies in."""
    sums = df.groupBy("part").agg(F.sum(value).alias("_sum"))  # a row for each range
    sums = sums.select("part", F.coalesce(F.sum("_sum").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_base"))
    inner = W.partitionBy("part").orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    return df.join(F.broadcast(sums), "part").withColumn(out, F.coalesce(F.sum(value).over(inner), F.lit(0)) + F.col("_base")).drop("_base")


def _by_name(column: str) -> Column:
    return F.col(column).asc_nulls_last()


def ranked(sizes: DataFrame, weights=WEIGHTS) -> DataFrame:
    """Adds ``part`` (a range of names) and the weight ``w`` of each source."""
    rows = sizes.repartitionByRange(C.shuffle_width(sizes.sparkSession), _by_name("source")).withColumns({"part": F.spark_partition_id(), "one": F.lit(1)})
    rows = _running(C.materialize(rows, "mix-ranges"), "one", "rank", _by_name("source"))
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.col("rank") % len(weights) + 1).cast("int"))
    return C.materialize(rows.withColumn("w", w).drop("one", "rank"), "mix-ranked")


def targets(sizes: DataFrame, share: float = 1.5, cap: float = 2.0, weights=WEIGHTS) -> DataFrame:
    """(source, source_size, part, target) from one row (source, source_size) for each
    source.

    Weights follow the order of the sources by code point, null last.  Every target is
    ``level * weight``, stopped at ``cap`` times the source's size.  The level at which all
    targets sum to ``share`` of all words is reached from below: what the stopped sources
    leave is spread over the others, until no further one stops."""
    rows = ranked(sizes, weights).withColumn("stop", cap * F.col("source_size"))
    level, stopped = 0.0, -1
    while True:
        over = F.col("stop") < F.lit(level) * F.col("w")
        got = rows.agg(
            F.sum("source_size").alias("words"), F.sum(over.cast("int")).alias("n"), F.sum(F.when(over, F.col("stop")).otherwise(0.0)).alias("full"), F.sum(F.when(over, 0.0).otherwise(F.col("w"))).alias("w")
        ).collect()[0]
        if not got["w"] or got["n"] == stopped:
            break
        stopped, level = got["n"], (share * got["words"] - got["full"]) / got["w"]
    target = F.col("stop") if got["w"] == 0 else F.least(F.col("stop"), F.lit(level) * F.col("w"))
    return rows.select("source", "source_size", "part", target.cast("double").alias("target"))


# ------------------------------------------------------------------ blocks and slots
def _tag(source: Column) -> Column:
    """A key without null."""
    return F.coalesce(F.concat(F.lit("v"), source), F.lit("n"))


def _bits(n: Column) -> Column:
    """Bits of the least power of two that holds n indices, 2 at least."""
    return F.greatest(F.lit(2), F.length(F.bin(F.greatest(n - 1, F.lit(0).cast("long")))))


def _feistel(x: Column, bits: Column, key: Column, rounds: int = 4) -> Column:
    """A keyed permutation of the numbers of so many bits."""
    few = F.floor(bits / 2).cast("int")
    many = bits - few
    one = F.lit(1).cast("long")
    mask = lambda b: F.call_function("shiftleft", one, b) - 1
    high, low = F.call_function("shiftright", x, many), x.bitwiseAND(mask(many))
    for i in range(rounds):
        if i % 2:
            low = low.bitwiseXOR(F.xxhash64(high, F.lit(i), key).bitwiseAND(mask(many)))
        else:
            high = high.bitwiseXOR(F.xxhash64(low, F.lit(i), key).bitwiseAND(mask(few)))
    return F.call_function("shiftleft", high, many).bitwiseOR(low)


def _once(value: Column, use) -> Column:
    """use(value), with the value computed once."""
    return F.get(F.transform(F.array(value), use), 0)


def permuted(x: Column, n: Column, key: Column, ahead: int = 3) -> Column:
    """Where a keyed permutation of 0 .. n - 1 sends x.  Of the walks half end at once, and
    half of the others at each further step; ``ahead`` steps are written out."""
    bits = _bits(n)
    turn = lambda y: _feistel(y, bits, key)

    def rest(y):
        far = F.aggregate(F.sequence(F.lit(1), F.lit(WALK)), y, lambda z, _: F.when(z < n, z).otherwise(turn(z)))
        return _once(far, lambda z: F.when(z < n, z).otherwise(F.raise_error(F.lit("a walk didn't end")).cast("long")))

    def walk(y, left):
        more = (lambda z: walk(z, left - 1)) if left else rest
        return F.when(y < n, y).otherwise(_once(turn(y), more))

    return _once(turn(x), lambda y: walk(y, ahead))


def _placed(docs: DataFrame, buckets: int) -> DataFrame:
    """Adds ``start``, the place of the first word in the source's stream."""
    rows = docs.withColumns({"tag": _tag(F.col("source")), "bucket": F.pmod(F.xxhash64("doc_id", F.lit("mix")), F.lit(buckets))})
    sums = C.materialize(rows.groupBy("tag", "bucket").agg(F.sum("size").alias("n")), "mix-buckets")
    run = W.partitionBy("tag").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    sums = C.materialize(sums.select("tag", "bucket", F.coalesce(F.sum("n").over(run), F.lit(0)).alias("base")), "mix-bases")
    inner = W.partitionBy("tag", "bucket").orderBy("doc_id", "row").rowsBetween(W.unboundedPreceding, -1)
    rows = rows.withColumn("start", F.coalesce(F.sum("size").over(inner), F.lit(0)))
    return rows.join(sums, ["tag", "bucket"]).withColumn("start", F.col("start") + F.col("base")).drop("base", "bucket")


def counted(plan: DataFrame, block: int) -> DataFrame:
    """Adds ``per_pass``, the slots of a whole pass, and ``n_slots``, all slots of a source,
    to (source_size, want)."""
    passes = F.floor(F.col("want") / F.greatest("source_size", F.lit(1)))
    rest = F.col("want") - passes * F.col("source_size")
    plan = plan.withColumn("per_pass", F.ceil(F.col("source_size") / block))
    return plan.withColumn("n_slots", F.when(F.col("want") > 0, passes * F.col("per_pass") + F.ceil(rest / block)).otherwise(0).cast("long"))


def _found(points: DataFrame, at: str, ranges: DataFrame, every: int) -> DataFrame:
    """Join each point to the range (lo <= point < hi) that holds it, by equal parts of all."""
    width = max(1, -(-every // RANGES))
    live = ranges.where("hi > lo")
    parts = live.withColumn("_bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1) / width))))
    met = points.withColumn("_bin", F.floor(F.col(at) / width)).join(parts, "_bin")
    return met.where((F.col(at) >= F.col("lo")) & (F.col(at) < F.col("hi"))).drop("_bin", "lo", "hi")


def draws(plan: DataFrame, shard_slots: int, seed: int) -> DataFrame:
    """(g, tag, number): for each slot of the mix its source and which of the source's slots
    it is, from (tag, part, n_slots) for each source."""
    spark = plan.sparkSession
    every = plan.agg(F.sum("n_slots")).collect()[0][0] or 0
    share = _running(plan.select("tag", "part", "n_slots"), "n_slots", "lo", "tag").withColumn("hi", F.col("lo") + F.col("n_slots"))
    share = C.materialize(share, "mix-share")
    u = F.shiftrightunsigned(F.xxhash64("g", F.lit(seed)), 11) / float(1 << 53)
    points = spark.range(0, every, 1, C.shuffle_width(spark)).select(F.col("id").alias("g"), F.least(F.floor(u * every), F.lit(every - 1)).alias("at"))
    drawn = _found(points, "at", share.select("tag", "lo", "hi", "n_slots"), every).select("g", "tag", "n_slots", F.floor(F.col("g") / RUN_SLOTS).alias("run"))
    drawn = C.materialize(drawn, "mix-draws")
    runs = drawn.groupBy("tag", "run").agg(F.count(F.lit(1)).alias("n"))
    runs = C.materialize(runs.withColumn("base", F.coalesce(F.sum("n").over(W.partitionBy("tag").orderBy("run").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))), "mix-runs")
    number = F.row_number().over(W.partitionBy("tag", "run").orderBy("g")) - 1 + F.col("base")
    numbered = C.materialize(drawn.join(runs.drop("n"), ["tag", "run"]).withColumn("number", number).select("g", "run", "tag", "number", "n_slots"), "mix-numbered")

    # draws too many of a source go, in order, to the sources with draws too few
    extra = numbered.where("number >= n_slots").select("g", "run")
    order = W.partitionBy("run").orderBy("g").rowsBetween(W.unboundedPreceding, -1)
    over = extra.groupBy("run").agg(F.count(F.lit(1)).alias("n"))
    over = over.select("run", F.coalesce(F.sum("n").over(W.orderBy("run").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    extra = extra.withColumn("_k", F.coalesce(F.sum(F.lit(1)).over(order), F.lit(0))).join(F.broadcast(over), "run").select("g", (F.col("_k") + F.col("base")).alias("at"))
    have = runs.groupBy("tag").agg(F.sum("n").alias("have"))
    lack = share.drop("lo", "hi").join(have, "tag", "left").withColumn("have", F.least("n_slots", F.coalesce("have", F.lit(0))))
    lack = _running(C.materialize(lack.withColumn("lack", F.col("n_slots") - F.col("have")), "mix-lack"), "lack", "lo", "tag")
    lack = C.materialize(lack.select("tag", "have", "lo", (F.col("lo") + F.col("lack")).alias("hi")), "mix-missing")
    moved = _found(extra, "at", lack.withColumn("first", F.col("lo")), every).select("g", "tag", (F.col("have") + F.col("at") - F.col("first")).alias("number"))
    return numbered.where("number < n_slots").select("g", "tag", "number").unionByName(moved)


def slots(plan: DataFrame, block: int, shard_slots: int, seed: int) -> DataFrame:
    """(tag, epoch, shard, slot, block, words): the block of each slot of each shard and how
    many of its words it takes, from (tag, part, source_size, want) for each source.

    Whole blocks are permuted; the short last block of a stream is the last slot of a pass."""
    plan = C.materialize(counted(plan, block), "mix-counted")
    rows = draws(plan, shard_slots, seed).join(plan.select("tag", "source_size", "want", "per_pass"), "tag")
    rows = rows.withColumns({"epoch": F.floor(F.col("number") / F.col("per_pass")), "i": F.col("number") % F.col("per_pass"), "n": F.floor(F.col("source_size") / block)})
    need = F.least("source_size", F.col("want") - F.col("epoch") * F.col("source_size"))
    at = F.when(F.col("i") < F.col("n"), permuted(F.col("i"), F.col("n"), F.xxhash64("tag", "epoch", F.lit(seed)))).otherwise(F.col("n"))
    return rows.select("tag", "epoch", F.floor(F.col("g") / shard_slots).alias("shard"), (F.col("g") % shard_slots).alias("slot"), at.alias("block"), F.least(F.lit(block), need - F.col("i") * block).alias("words"))


def mix(docs: DataFrame, block: int = BLOCK, shard_slots: int = SHARD_SLOTS, seed: int = 17) -> DataFrame:
    """Mix the rows (doc_id, text, source): doc_id, row, source, size, source_size, target,
    taken, pieces.

    ``pieces``: the mix's parts of a document, as (epoch, lo, hi, shard, slot) for words
    lo to hi - 1; ``row``: a hash of the text, to find it again; ``taken``: their words."""
    C.need(docs, "doc_id", "text", "source")
    sized = docs.select("doc_id", "source", C.word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("row"))
    sized = C.materialize(sized, "mix-sizes")
    totals = C.materialize(sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("docs")), "mix-sources")
    plan = targets(totals.select("source", "source_size"))
    plan = C.materialize(plan.withColumns({"tag": _tag(F.col("source")), "want": F.round("target").cast("long")}), "mix-plan")
    taken = C.materialize(slots(plan.select("tag", "part", "source_size", "want"), block, shard_slots, seed), "mix-slots")
    most = totals.agg(F.max("docs")).collect()[0][0] or 0
    buckets = max(256, -(-most // BUCKET_ROWS))
    first, last = F.floor(F.col("start") / block), F.floor((F.col("start") + F.col("size") - 1) / block)
    parts = _placed(sized, buckets).withColumn("block", F.explode_outer(F.when(F.col("size") > 0, F.sequence(first, last))))
    lo, hi = F.greatest("start", F.col("block") * block), F.least(F.col("start") + F.col("size"), F.col("block") * block + F.col("words"))
    piece = F.struct("epoch", (lo - F.col("start")).alias("lo"), (hi - F.col("start")).alias("hi"), "shard", "slot")
    # sizes of unfolded rows are underestimated: merge joins, so that nothing large is broadcast
    met = parts.join(taken.hint("merge"), ["tag", "block"], "left").withColumn("piece", F.when(F.col("slot").isNotNull() & (hi > lo), piece))
    out = met.groupBy("tag", "start", "size", "doc_id", "row", "source").agg(
        F.sum(F.coalesce(F.col("piece.hi") - F.col("piece.lo"), F.lit(0))).alias("taken"), F.sort_array(F.collect_list("piece")).alias("pieces")
    )
    zero = sized.where("size = 0").select("doc_id", "row", "source", "size", F.lit(0).cast("long").alias("taken"), F.expr("array()").cast(out.schema["pieces"].dataType).alias("pieces"))
    every = out.where("size > 0").select("doc_id", "row", "source", "size", "taken", "pieces").unionByName(zero)
    return every.withColumn("tag", _tag(F.col("source"))).join(plan.select("tag", "source_size", "target"), "tag").select("doc_id", "row", "source", "size", "source_size", "target", "taken", "pieces")


def mixed_texts(docs: DataFrame, **options) -> DataFrame:
    """The mix as rows of ``docs``: one for each document and pass that takes words of it,
    the text unchanged if the pass takes all of it, else the words taken, by blanks."""
    picked = mix(docs, **options).where("taken > 0").select("doc_id", "row", "size", "pieces")
    by_pass = F.transform(F.array_distinct(F.transform("pieces", lambda p: p["epoch"])), lambda e: F.filter("pieces", lambda p: p["epoch"] == e))
    picked = picked.withColumn("_pass", F.explode(by_pass)).withColumnsRenamed({"doc_id": "_id", "row": "_row", "size": "_size"}).drop("pieces")
    texts = docs.withColumn("_row2", F.xxhash64("text"))
    texts = texts.dropDuplicates(["doc_id", "_row2"]) if docs.columns else texts
    full = texts.join(picked.hint("merge"), (F.col("doc_id").eqNullSafe(F.col("_id"))) & (F.col("_row2") == F.col("_row")))
    words = F.filter(F.split("text", C.GAP), lambda w: w != "")
    some = F.array_join(F.flatten(F.transform(F.sort_array(F.transform("_pass", lambda p: F.struct(p["lo"].alias("lo"), p["hi"].alias("hi")))), lambda p: F.slice(words, p["lo"].cast("int") + 1, (p["hi"] - p["lo"]).cast("int")))), " ")
    whole = F.aggregate("_pass", F.lit(0).cast("long"), lambda a, p: a + p["hi"] - p["lo"]) == F.col("_size")
    return full.withColumn("text", F.when(whole, F.col("text")).otherwise(some)).select(*docs.columns)


def op5_mixing(spark, sf_dir: str) -> DataFrame:
    with C.Scratch(spark) as tables:
        out = mix(C.read_table(spark, sf_dir, "documents", "doc_id", "text", "source"))
        return tables.keep(out.select("doc_id", "size", "source_size", "target", "taken"), "mix-result")
