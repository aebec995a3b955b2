"""Near-duplicate documents: MinHash signatures joined by a multi-index Hamming join.

A document's set holds the hashes of its distinct word shingles.  Its signature has
``CHUNKS * CHUNK`` MinHash symbols of 16 bits.  Two signatures that differ in fewer than
``2 * CHUNKS`` symbols agree, by the pigeonhole principle, in all symbols but one of some
chunk; so the keys of a chunk leave out each symbol in turn (its allowed error), and every
pair under that distance shares a key.  At a similarity of 0.8 a chunk of four symbols has
at most one error with probability 0.82, and all eight chunks fail together in one of a
million pairs.

Only connectivity is wanted, so pairs inside a group of copies aren't all formed:

1. documents of equal sets are one class, named by a digest of the set;
2. members of a key are compared with the key's leader (another leader each round), and
   confirmed links join components; a leader's members are dealt to groups of bounded
   size, each of which gets the leader's text;
3. members of keys that still hold several components are dealt to blocks of bounded
   size, and pairs of blocks that share a key are compared set by set in one task each.

Steps 1 to 3 find every component that comparing all pairs of a key would find, without
a row for each pair of a group.  Links are confirmed on full sets.  Texts travel compressed,
and only those of documents with a candidate.

Edge cases: null or empty text has an empty set and links with nothing; rows of null id
link with nothing (component null, kept); rows of one id lie in one component, whatever
their texts (but for those without words), and each text's links are found on that text;
other columns aren't read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

CHUNKS, CHUNK = 8, 4
LEADER_ROUNDS = 2
BLOCK_SHINGLES = 40_000  # of a block, about; bounds the memory of a comparison
LEADER_SHINGLES = 200_000  # of the members that one group of a leader holds, about
_A = C.stream64(CHUNKS * CHUNK, 21) | np.uint64(1)
_B = C.stream64(CHUNKS * CHUNK, 22)


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """Sorted distinct hashes of the k-word shingles of each text (ASCII lower case)."""
    words = C.Words(texts, lower=True)
    h, out = words.hashes(), []
    for a, b in zip(words.ptr[:-1], words.ptr[1:]):
        n = b - a
        out.append(np.unique(C.window_hashes(h[a:b], k)) if n >= k else C.window_hashes(h[a:b] + np.uint64(n), n) if n else np.zeros(0, np.uint64))
    return out


def signature(s: np.ndarray) -> np.ndarray:
    low = np.full(len(_A), np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(s), 4096):
        np.minimum(low, (s[i : i + 4096, None] * _A + _B).min(axis=0), out=low)
    return (C.mix64(low) & np.uint64(0xFFFF)).astype(np.uint16)


def set_key(s: np.ndarray) -> bytes:
    """128 bits that stand for the whole set."""
    import hashlib

    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


_SIGNED = pa.schema([("doc_id", pa.int64()), ("th", pa.int64()), ("n_shingles", pa.int64()), ("set_key", pa.binary()), ("sig", pa.binary())])


def _sign(k: int):
    def run(batches):
        for batch in batches:
            ids, th = batch.column("doc_id"), batch.column("th")
            for a, b, texts in C.text_batches(batch):
                sets = shingle_sets(texts, k)
                yield pa.record_batch([ids.slice(a, b - a), th.slice(a, b - a), pa.array([len(s) for s in sets], pa.int64()), pa.array([set_key(s) if len(s) else None for s in sets], pa.binary()), pa.array([signature(s).tobytes() if len(s) else None for s in sets], pa.binary())], schema=_SIGNED)

    return run


def signature_keys(sig: np.ndarray) -> np.ndarray:
    """(n, CHUNKS * CHUNK) keys: for each chunk the symbols left when one is left out."""
    sig = sig.reshape(-1, CHUNKS, CHUNK).astype(np.uint64)
    out = []
    for c in range(CHUNKS):
        for skip in range(CHUNK):
            key = np.full(len(sig), c * CHUNK + skip, np.uint64)
            for j in range(CHUNK):
                if j != skip:
                    key = (key << np.uint64(16)) ^ sig[:, c, j]
            out.append(C.mix64(key))
    return np.stack(out, axis=1)


def _keys(batches):
    for batch in batches:
        if not batch.num_rows:
            continue
        sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), np.uint16)
        keys = signature_keys(sig).view(np.int64)
        m = keys.shape[1]
        which = pa.array(np.repeat(np.arange(batch.num_rows), m))
        yield pa.record_batch([pa.array(keys.reshape(-1)), batch.column("node").take(which), batch.column("n").take(which)], names=["key", "node", "n"])


def _pack(batches):
    z = zstandard.ZstdCompressor(level=1)
    for batch in batches:
        ids, th = batch.column("doc_id"), batch.column("th")
        for a, b, texts in C.text_batches(batch):
            yield pa.record_batch([ids.slice(a, b - a), th.slice(a, b - a), pa.array([z.compress(t) for t in texts], pa.binary())], names=["doc_id", "th", "z"])


def _confirm(k: int, percent: int):
    def run(batches):
        z, last, of_last = zstandard.ZstdDecompressor(), None, None
        for batch in batches:
            good_a, good_b = [], []
            ids_a, ids_b = batch.column("a").to_pylist(), batch.column("b").to_pylist()
            za, zb = batch.column("za"), batch.column("zb")
            for lo, hi in C.runs([zstandard.frame_content_size(x.as_py()) for x in za], C.BATCH_BYTES):
                sets = shingle_sets([z.decompress(za[i].as_py()) for i in range(lo, hi)], k)
                for i, s in zip(range(lo, hi), sets):
                    if ids_b[i] != last:
                        last, of_last = ids_b[i], shingle_sets([z.decompress(zb[i].as_py())], k)[0]
                    t = of_last
                    both = len(np.intersect1d(s, t, assume_unique=True))
                    if 100 * both >= percent * (len(s) + len(t) - both):
                        good_a.append(ids_a[i])
                        good_b.append(ids_b[i])
            yield pa.record_batch([pa.array(good_a, pa.binary()), pa.array(good_b, pa.binary())], names=["a", "b"])

    return run


def _mixed(rows: DataFrame, key: str) -> DataFrame:
    """The keys under which several components lie."""
    return C.materialize(rows.groupBy(key).agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high").select(key), "near-mixed")


def _load_block(docs: list[dict], k: int, z) -> tuple[list[bytes], list[bytes], list[np.ndarray]]:
    sets = shingle_sets([z.decompress(d["z"]) for d in docs], k)
    return [d["node"] for d in docs], [d["comp"] for d in docs], sets


def _overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections, from incidence matrices over the common shingles."""
    common = np.intersect1d(np.concatenate(left), np.concatenate(right))
    out = np.zeros((len(left), len(right)), np.float32)
    for lo in range(0, len(common), 8192):
        part = common[lo : lo + 8192]
        make = lambda sets: np.stack([np.isin(part, s, assume_unique=True) for s in sets]).astype(np.float32)
        out += make(left) @ make(right).T
    return out.astype(np.int64)


def _cross(k: int, percent: int):
    """Links between two blocks: for each document one of each other component."""

    def run(batches):
        z, last, kept = zstandard.ZstdDecompressor(), None, None
        for batch in batches:
            for i in range(batch.num_rows):
                x = batch.column("x")[i].as_py()
                if x != last:
                    last, kept = x, _load_block(batch.column("left")[i].as_py(), k, z)
                a, ca, left = kept
                b, cb, right = _load_block(batch.column("right")[i].as_py(), k, z)
                na, nb = np.array([len(s) for s in left]), np.array([len(s) for s in right])
                both = _overlaps(left, right)
                _, comp = np.unique(np.array(ca + cb, object), return_inverse=True)
                of_a, of_b = comp[: len(a)], comp[len(a) :]
                hit = (100 * both >= percent * (na[:, None] + nb - both)) & (of_a[:, None] != of_b)
                p, q = np.nonzero(hit)
                _, one = np.unique(np.stack([p, of_b[q]], axis=1), axis=0, return_index=True) if len(p) else (None, [])
                yield pa.record_batch([pa.array([a[p[i]] for i in one], pa.binary()), pa.array([b[q[i]] for i in one], pa.binary())], names=["a", "b"])

    return run


class _Search:
    """Confirms candidate pairs (a, na, b, nb) of classes on their texts (node, z)."""

    def __init__(self, texts: DataFrame, k: int, percent: int):
        self.texts, self.k, self.percent = texts, k, percent

    def confirmed(self, pairs: DataFrame, tag: str) -> DataFrame:
        p = self.percent
        pairs = pairs.where(f"a <> b AND 100 * least(na, nb) >= {p} * greatest(na, nb)").select("a", "b", "na").distinct()
        pairs = C.materialize(pairs, f"near-pairs{tag}")
        groups = pairs.groupBy("b").agg(F.ceil(F.sum("na") / LEADER_SHINGLES).alias("groups"))
        groups = C.materialize(groups, f"near-groups{tag}")
        group = F.pmod(F.xxhash64("a"), F.col("groups")).alias("g")
        dealt = pairs.join(groups, "b").select("a", "b", group).join(self.texts.select(F.col("node").alias("a"), F.col("z").alias("za")), "a")
        lead = groups.select("b", F.explode(F.sequence(F.lit(0).cast("long"), F.col("groups") - 1)).alias("g"))
        lead = lead.join(self.texts.select(F.col("node").alias("b"), F.col("z").alias("zb")), "b")
        full = dealt.join(lead.hint("merge"), ["b", "g"]).select("a", "b", "za", "zb")
        return C.materialize(full.mapInArrow(_confirm(self.k, p), "a binary, b binary"), f"near-links{tag}")

    def blocks(self, todo: DataFrame) -> DataFrame:
        """Compare all that is left; a class's block lies at its least key leader."""
        low = C.materialize(todo.groupBy("key").agg(F.min("node").alias("low")), "near-low")
        home = C.materialize(todo.join(low, "key").groupBy("node", "n", "comp").agg(F.min("low").alias("home")), "near-home")
        parts = C.materialize(home.groupBy("home").agg(F.ceil(F.sum("n") / BLOCK_SHINGLES).alias("parts")), "near-parts")
        placed = home.join(parts, "home").select("node", "comp", F.xxhash64("home", F.pmod(F.xxhash64("node"), F.col("parts"))).alias("block"))
        placed = C.materialize(placed, "near-placed")
        at = C.materialize(todo.select("key", "node").join(placed, "node").groupBy("key", "block").agg(F.min("comp").alias("low"), F.max("comp").alias("high")), "near-at")
        other = at.select("key", F.col("block").alias("y"), F.col("low").alias("low2"), F.col("high").alias("high2"))
        mixed = "least(low, low2) <> greatest(high, high2)"
        pairs = at.withColumnRenamed("block", "x").join(other, "key").where(f"x < y AND {mixed}").select("x", "y")
        pairs = C.materialize(pairs.union(at.where("low <> high").select(F.col("block").alias("x"), F.col("block").alias("y"))).distinct(), "near-block-pairs")
        packed = placed.join(self.texts, "node").groupBy("block").agg(F.collect_list(F.struct("node", "comp", "z")).alias("docs"))
        packed = C.materialize(packed, "near-blocks")
        full = pairs.join(packed.select(F.col("block").alias("y"), F.col("docs").alias("right")), "y").join(packed.select(F.col("block").alias("x"), F.col("docs").alias("left")), "x")
        return C.materialize(full.select("x", "left", "right").mapInArrow(_cross(self.k, self.percent), "a binary, b binary"), "near-block-links")


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of ``docs`` (doc_id, text)."""
    C.need(docs, "doc_id", "text")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")
    with C.Scratch(docs.sparkSession) as tables:
        signed = C.materialize(docs.mapInArrow(_sign(k), "doc_id long, th long, n_shingles long, set_key binary, sig binary"), "near-signed")
        usable = signed.where("doc_id IS NOT NULL AND n_shingles > 0")
        classes = usable.groupBy(F.col("set_key").alias("node")).agg(F.min(F.struct("doc_id", "th")).alias("rep"), F.first("n_shingles").alias("n"), F.first("sig").alias("sig"))
        classes = C.materialize(classes.select("node", "rep.doc_id", "rep.th", "n", "sig"), "near-classes")
        links = _links(docs, classes, k, percent)
        several = usable.groupBy("doc_id").agg(F.min("set_key").alias("a"), F.max("set_key").alias("z")).where("a <> z").select("doc_id", "a")
        links = links.union(usable.join(several, "doc_id").where("set_key <> a").select("a", F.col("set_key").alias("b")))
        label = classes.select("node", "doc_id").join(C.components(links), "node", "left").select("node", "doc_id", F.coalesce("component", "node").alias("component"))
        label = C.materialize(label, "near-label")
        least = label.groupBy("component").agg(F.min("doc_id").alias("component_id"))
        member = label.join(least, "component").select(F.col("node").alias("set_key"), "component_id")
        out = signed.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.col("set_key")).alias("set_key")).join(member, "set_key", "left")
        out = out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))
        return tables.keep(out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))), "near-result")


def _links(docs: DataFrame, classes: DataFrame, k: int, percent: int) -> DataFrame:
    """(a, b): links that join all classes of a component."""
    keys = classes.select("node", "n", "sig").mapInArrow(_keys, "key long, node binary, n long")
    shared = keys.groupBy("key").agg(F.min("node").alias("low"), F.max("node").alias("high")).where("low <> high").select("key")
    shared = C.materialize(shared, "near-shared")
    keys = C.materialize(keys.join(shared, "key"), "near-keys")
    wanted = classes.join(keys.select("node").distinct(), "node", "left_semi").select("node", "doc_id", "th")
    packed = docs.mapInArrow(_pack, "doc_id long, th long, z binary")
    texts = C.materialize(packed.join(wanted, ["doc_id", "th"]).select("node", "z").dropDuplicates(["node"]), "near-texts")
    search = _Search(texts, k, percent)

    links = docs.sparkSession.createDataFrame([], "a binary, b binary")
    todo = keys.select("key", "node", "n", F.col("node").alias("comp"))
    for rnd in range(LEADER_ROUNDS):
        if todo.isEmpty():
            break
        first = F.struct(F.xxhash64(F.lit(rnd), "node").alias("r"), F.col("node").alias("b"), F.col("n").alias("nb"), F.col("comp").alias("cb"))
        lead = C.materialize(todo.groupBy("key").agg(F.min(first).alias("m")).select("key", "m.b", "m.nb", "m.cb"), f"near-lead{rnd}")
        pairs = todo.select("key", F.col("node").alias("a"), F.col("n").alias("na"), "comp").join(lead, "key").where("comp <> cb")
        links = links.union(search.confirmed(pairs, f"{rnd}"))
        label = C.components(links)
        now = keys.join(label, "node", "left").select("key", "node", "n", F.coalesce("component", "node").alias("comp"))
        now = C.materialize(now, f"near-now{rnd}")
        todo = C.materialize(now.join(_mixed(now, "key"), "key"), f"near-todo{rnd}")
    return links if todo.isEmpty() else links.union(search.blocks(todo))


def without_near_duplicates(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` but for those whose component has a document of less id."""
    with C.Scratch(docs.sparkSession) as tables:
        gone = tables.keep(near_duplicates(docs, k, percent).where("NOT kept").select(F.col("doc_id").alias("_gone")).distinct(), "near-gone")
    return docs.join(gone, F.col("doc_id") == F.col("_gone"), "left_anti")


def op4_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(C.read_table(spark, sf_dir, "documents", "doc_id", "text"), k=4, percent=80)
