"""Near-duplicate embeddings: iterative quantisation, multi-index Hamming tables, rerank.

Rotations of the centred vectors are learned on a bounded sample so that their signs are
balanced binary codes that lose little (iterative quantisation: principal axes, then
alternating signs and Procrustes rotations).  A code is cut in chunks; two codes that differ
in fewer bits than there are chunks agree in one of them, which makes them candidates.  The
width of a chunk follows the number of vectors of a label, so that chance agreements stay
few for each vector however many there are; the number of chunks is the least at which
``RECALL`` of simulated pairs of just the least cosine share a chunk.  Candidates are
compared by the cosine of the original vectors, in double precision.

Equal vectors of a label are one class.  A pair is looked at only under the first chunk it
shares.  Members of small buckets are paired by their codes (a Hamming radius drops chance
agreements) and then compared; larger buckets are dealt to blocks of bounded size, and two
blocks of a bucket are compared by one matrix product, which reports link counts and a
spanning forest: no row is made for each pair of a large group.

Vectors of all lengths are searched (only equal lengths link).  Lengths that are rare in the
sample get random hyperplanes in place of learned rotations.

Edge cases: vectors that are null, empty, zero, or hold null or non-finite components link
with nothing, nor do those of null label; a vector's scale doesn't matter, however large or
small; rows of null vec_id link with nothing and are kept; repeated rows are links of each
other; rows of one vec_id with several vectors lie in one component and count links each
by its own vector; an empty table gives an empty result; other columns aren't read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

SAMPLE = 4000  # vectors that rotations are learned on, at most
LEAST_SAMPLE = 200  # of a length, to learn its rotations
RECALL = 0.997  # of simulated pairs at the least cosine
TABLES = 64  # chunks, at most
SMALL = 16  # members of a bucket whose candidates are paired one by one
BLOCK = 400  # vectors of a block of a larger bucket, about
ROUNDS = 40


# ------------------------------------------------------------------ the rotations
class Quantiser:
    """Signs of rotated, centred vectors."""

    def __init__(self, mean: np.ndarray, turn: np.ndarray):
        self.mean, self.turn = mean, turn

    def bits(self, x: np.ndarray) -> np.ndarray:
        return (x - self.mean) @ self.turn >= 0


def learn(x: np.ndarray, rounds: int = ROUNDS, seed: int = 3) -> Quantiser:
    """Iterative quantisation of unit vectors to as many bits as they have coordinates."""
    mean = x.mean(axis=0)
    _, axes = np.linalg.eigh(np.cov((x - mean).T).reshape(x.shape[1], -1) + 1e-12 * np.eye(x.shape[1]))
    v = (x - mean) @ axes[:, ::-1]
    turn = np.linalg.qr(np.random.default_rng(seed).normal(size=(v.shape[1], v.shape[1])))[0]
    for _ in range(rounds):
        code = np.where(v @ turn >= 0, 1.0, -1.0)
        u, _, w = np.linalg.svd(v.T @ code)
        turn = u @ w
    return Quantiser(mean, axes[:, ::-1] @ turn)


class Tables:
    """The chunks of all codes: ``count`` chunks of ``width`` bits, and the radius (in bits
    of the whole code) beyond which pairs of a small bucket aren't compared."""

    def __init__(self, width: int, count: int, radius: int, learned: dict[int, Quantiser]):
        self.width, self.count, self.radius, self.learned = width, count, radius, learned
        self.kind = np.uint16 if width <= 16 else np.uint32 if width <= 32 else np.uint64

    def codes(self, x: np.ndarray) -> np.ndarray:
        """(n, count) chunk values of unit vectors of one length."""
        d, bits = x.shape[1], self.width * self.count
        q = self.learned.get(d) or Quantiser(np.zeros(d), np.random.default_rng(d).normal(size=(d, bits)))
        return chunked(q.bits(x)[:, :bits], self.width).astype(self.kind)


def chunked(bits: np.ndarray, width: int) -> np.ndarray:
    n = bits.shape[1] // width
    return bits[:, : n * width].reshape(len(bits), n, width) @ (np.uint64(1) << np.arange(width, dtype=np.uint64))


def _several(x: np.ndarray, bits: int) -> Quantiser:
    """Learned rotations side by side, until there are enough bits."""
    each = [learn(x, seed=3 + k) for k in range(-(-bits // x.shape[1]))]
    return Quantiser(each[0].mean, np.concatenate([q.turn for q in each], axis=1))


def simulated_pairs(x: np.ndarray, least: float, n: int = 3000, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors of the sample, and others at just the least cosine from them, moved
    towards further vectors of the sample."""
    rng = np.random.default_rng(seed)
    a, b = x[rng.integers(0, len(x), n)], x[rng.integers(0, len(x), n)]
    off = b - (a * b).sum(axis=1, keepdims=True) * a
    size = np.linalg.norm(off, axis=1)
    a, off = a[size > 1e-6], off[size > 1e-6] / size[size > 1e-6, None]
    return a, least * a + np.sqrt(max(0.0, 1 - least * least)) * off


def plan_tables(samples: dict[int, np.ndarray], largest: int, least: float) -> Tables:
    """Chunk width by the vectors of the largest label, number of chunks by simulation."""
    width = int(min(60, max(6, np.ceil(np.log2(max(largest, 2))) + 1)))
    main = max(samples.values(), key=len, default=np.zeros((0, 2)))
    if len(main) < LEAST_SAMPLE or main.shape[1] < 2:
        main = np.random.default_rng(1).normal(size=(2000, 32))
        main /= np.linalg.norm(main, axis=1, keepdims=True)
    a, b = simulated_pairs(main, least)
    while True:
        q = _several(main, width * 8)
        while True:
            have = q.turn.shape[1] // width
            x, y = chunked(q.bits(a), width), chunked(q.bits(b), width)
            reached = np.maximum.accumulate(x == y, axis=1).mean(axis=0) if len(a) else np.ones(have)
            good = np.flatnonzero(reached >= RECALL)
            if len(good) or have >= TABLES:
                break
            q = _several(main, min(TABLES, 2 * have) * width)
        if len(good) or width <= 6:
            break
        width -= 1  # codes of these vectors say too little: wider buckets
    count = int(good[0]) + 1 if len(good) else have
    far = np.bitwise_count(x[:, :count] ^ y[:, :count]).sum(axis=1) if len(a) else np.array([0])
    learned = {d: _several(s, width * count) for d, s in samples.items() if len(s) >= LEAST_SAMPLE}
    return Tables(width, count, int(far.max() * 1.25) + 2, learned)


# ------------------------------------------------------------------ the stages
def unit_rows(raw: list[bytes]) -> np.ndarray:
    """Vectors of one length, scaled to length one without overflow."""
    x = np.frombuffer(b"".join(raw), np.float64).reshape(len(raw), -1)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _usable(batches):
    """All rows; those that can link have their components as bytes in v."""
    for batch in batches:
        out = []
        for i, x, k in zip(batch.column("vec_id").to_pylist(), batch.column("embedding").to_pylist(), batch.column("label").to_pylist()):
            v = None
            if i is not None and k is not None and x and None not in x:
                v = np.array(x, np.float64) + 0.0
                v = v.tobytes() if np.isfinite(v).all() and v.any() else None
            out.append(v)
        yield pa.record_batch([batch.column("vec_id"), batch.column("label"), pa.array(out, pa.binary())], names=["vec_id", "label", "v"])


def _keys(sent):
    """A row for each class and chunk: key, place of the chunk, node, code."""

    def run(batches):
        tables = sent.value
        for batch in batches:
            raw, label = batch.column("v").to_pylist(), batch.column("label").to_numpy()
            node, size = batch.column("node"), np.array([len(v) for v in raw], np.int64)
            for n in np.unique(size):
                at = np.flatnonzero(size == n)
                code = tables.codes(unit_rows([raw[i] for i in at]))
                base = C.mix64(label[at].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(n))
                key = C.mix64(C.mix64(base[:, None] + np.arange(tables.count, dtype=np.uint64)) ^ C.mix64(code))
                which = np.repeat(at, tables.count)
                blob = pa.array([c.tobytes() for c in code], pa.binary())
                yield pa.record_batch([pa.array(key.view(np.int64).reshape(-1)), pa.array(np.tile(np.arange(tables.count, dtype=np.int32), len(at))), node.take(pa.array(which)), blob.take(pa.array(np.repeat(np.arange(len(at)), tables.count)))], names=["key", "chunk", "node", "code"])

    return run


def _first_shared(x: np.ndarray, y: np.ndarray, chunk: np.ndarray) -> np.ndarray:
    """Whether the codes (rows of chunks) share no chunk before ``chunk``."""
    same = x == y
    return same.argmax(axis=1) == chunk if len(same) else np.zeros(0, bool)


def _pairs(sent):
    """Candidates of small buckets; rows come sorted by key."""

    def found(rows):
        tables, key = sent.value, rows.column("key").to_numpy()
        chunk, node = rows.column("chunk").to_numpy(), rows.column("node")
        code = np.frombuffer(b"".join(rows.column("code").to_pylist()), tables.kind).reshape(len(key), -1)
        left, right = [], []
        for step in range(1, SMALL):
            a = np.flatnonzero(key[step:] == key[:-step])
            if not len(a):
                break
            x, y = code[a], code[a + step]
            good = (np.bitwise_count(x ^ y).sum(axis=1) <= tables.radius) & _first_shared(x, y, chunk[a])
            left.append(a[good])
            right.append(a[good] + step)
        join = lambda parts: pa.array(np.concatenate(parts) if parts else np.zeros(0, np.int64))
        return pa.record_batch([node.take(join(left)), node.take(join(right))], names=["a", "b"])

    def run(batches):
        held = None
        for batch in batches:
            if not batch.num_rows:
                continue
            held = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            key = held.column("key").to_numpy()
            cut = int(np.flatnonzero(key == key[-1])[0])  # the last bucket may go on
            if cut:
                yield found(held.slice(0, cut))
                held = held.slice(cut)
        if held is not None:
            yield found(held)

    return run


def _rerank(least: float):
    def run(batches):
        for batch in batches:
            va, vb = batch.column("va").to_pylist(), batch.column("vb").to_pylist()
            good = np.zeros(len(va), bool)
            size = np.array([len(x) if len(x) == len(y) else 0 for x, y in zip(va, vb)], np.int64)
            for n in np.unique(size[size > 0]):
                at = np.flatnonzero(size == n)
                good[at] = (unit_rows([va[i] for i in at]) * unit_rows([vb[i] for i in at])).sum(axis=1) >= least
            keep = batch.filter(pa.array(good))
            both = lambda x, y: pa.concat_arrays([keep.column(x), keep.column(y)])
            yield pa.record_batch([both("a", "b"), both("b", "a"), both("nb", "na")], names=["a", "b", "links"])

    return run


def _forest(hit: np.ndarray) -> np.ndarray:
    """For each row the least member of its component, as places; hit is symmetric."""
    low = np.arange(len(hit))
    while True:
        new = np.minimum(low, np.where(hit, low[None], len(hit)).min(axis=1, initial=len(hit)))
        if (new == low).all():
            return low
        low = new


_FOUND = pa.schema([("a", pa.binary()), ("b", pa.binary()), ("links", pa.int64())])


def _compare(least: float, kind):
    """Links within a block of a bucket, or between two blocks of it."""

    def run(key, table):
        p, q = key[1].as_py(), key[2].as_py()
        node, part = table.column("node").to_pylist(), table.column("part").to_numpy()
        chunk, size, label = table.column("chunk").to_numpy(), table.column("size").to_numpy(), table.column("label").to_numpy()
        raw = table.column("v").to_pylist()
        code = np.frombuffer(b"".join(table.column("code").to_pylist()), kind).reshape(len(node), -1)
        length = np.array([len(v) for v in raw])
        hit = np.zeros((len(node), len(node)), bool)
        for n in np.unique(length):
            at = np.flatnonzero(length == n)
            u = unit_rows([raw[i] for i in at])
            hit[np.ix_(at, at)] = u @ u.T >= least
        np.fill_diagonal(hit, False)
        hit &= (label[:, None] == label) & (chunk[:, None] == chunk)
        if p != q:
            hit &= part[:, None] != part
        a, b = np.nonzero(hit)
        hit[a, b] = _first_shared(code[a], code[b], chunk[a])
        root, links = _forest(hit), hit @ size
        at = np.flatnonzero(links)
        return pa.table([pa.array([node[i] for i in at], pa.binary()), pa.array([node[root[i]] for i in at], pa.binary()), pa.array(links[at].astype(np.int64))], schema=_FOUND)

    return run


def near_vectors(vectors: DataFrame, least: float = 0.98) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of each row (vec_id, embedding, label)."""
    C.need(vectors, "vec_id", "embedding", "label")
    spark = vectors.sparkSession
    with C.Scratch(spark) as tables:
        rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").cast("array<double>").alias("embedding"))
        node = F.when(F.col("v").isNotNull(), F.unhex(F.md5(F.concat(F.col("label").cast("string").cast("binary"), F.lit(b":"), F.col("v")))))
        rows = C.materialize(rows.mapInArrow(_usable, "vec_id long, label long, v binary").withColumn("node", node), "emb-rows")
        classes = C.materialize(rows.where("node IS NOT NULL").groupBy("node").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("size"), F.first("label").alias("label"), F.first("v").alias("v")), "emb-classes")
        largest = classes.groupBy("label").count().agg(F.max("count")).collect()[0][0] or 0
        plain = {}
        for r in classes.select("v").orderBy("node").limit(SAMPLE).collect():  # digests are a random order
            plain.setdefault(len(r["v"]) // 8, []).append(r["v"])
        plan = plan_tables({d: unit_rows(v) for d, v in plain.items()}, largest, least)
        sent = spark.sparkContext.broadcast(plan)

        keys = C.materialize(classes.select("node", "label", "v").mapInArrow(_keys(sent), "key long, chunk int, node binary, code binary"), "emb-keys")
        shared = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
        shared = C.materialize(keys.join(shared, "key"), "emb-shared")
        small = shared.where(F.col("n") <= SMALL).select("key", "chunk", "node", "code").repartition(C.shuffle_width(spark), "key").sortWithinPartitions("key")
        pairs = C.materialize(small.mapInArrow(_pairs(sent), "a binary, b binary"), "emb-pairs")
        side = lambda c: classes.select(F.col("node").alias(c), F.col("v").alias(f"v{c}"), F.col("label").alias(f"l{c}"), F.col("size").alias(f"n{c}"))
        full = pairs.join(side("a"), "a").join(side("b"), "b").where("la = lb").select("a", "b", "va", "vb", "na", "nb")
        found = full.mapInArrow(_rerank(least), "a binary, b binary, links long")

        parts = F.ceil(F.col("n") / BLOCK)
        part = F.pmod(F.xxhash64("node"), parts)
        other = F.explode(F.sequence(F.lit(0).cast("long"), parts - 1))
        large = shared.where(F.col("n") > SMALL).select("key", "chunk", "node", "code", part.alias("part"), other.alias("other"))
        large = large.join(classes.select("node", "size", "label", "v"), "node").withColumns({"p": F.least("part", "other"), "q": F.greatest("part", "other")})
        found = found.union(large.groupBy("key", "p", "q").applyInArrow(_compare(least, plan.kind), "a binary, b binary, links long"))
        found = C.materialize(found, "emb-found")

        links = found.groupBy("a").agg(F.sum("links").alias("links")).withColumnRenamed("a", "node")
        ids = rows.where("node IS NOT NULL").groupBy("vec_id").agg(F.min("node").alias("a"), F.max("node").alias("z")).where("a <> z").select("vec_id", "a")
        ids = rows.join(ids, "vec_id").where("node IS NOT NULL AND node <> a").select("a", F.col("node").alias("b"))
        label = C.components(found.select("a", "b").union(ids))
        label = C.materialize(classes.select("node", "rep").join(label, "node", "left").withColumn("component", F.coalesce("component", "node")), "emb-label")
        least_id = label.groupBy("component").agg(F.min("rep").alias("component_id"))
        state = label.join(least_id, "component").join(classes.select("node", "size"), "node").join(links, "node", "left")
        state = C.materialize(state.select("node", (F.col("size") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), "component_id"), "emb-state")
        out = rows.select("vec_id", "node").join(state, "node", "left")
        out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
        return tables.keep(out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True))), "emb-result")


def op9_embedding_dedup(spark, sf_dir: str) -> DataFrame:
    return near_vectors(C.read_table(spark, sf_dir, "embeddings", "vec_id", "embedding", "label"))
