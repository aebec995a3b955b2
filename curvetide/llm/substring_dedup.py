"""Substring dedup: words inside windows that an earlier document also has are removed.

A window is ``window`` consecutive words.  Documents are packed in chunks of bounded size.
Each window is represented by its anchor, the least hash of the short runs of words inside
it, so equal windows have equal anchors wherever they stand:

1. anchors go to shards by hash; those seen in one document only are dropped;
2. stretches of windows with a common, repeated anchor go to the anchor's shard, equal
   stretches of a chunk once;
3. each shard builds an FM-index of the stretches of an anchor's earlier documents (all but
   the last one that has it), and streams those of its later documents (all but the
   first one) through it: backward search gives the interval of each window that the
   index holds, and with it the least document; other windows match nothing;
4. chunks get these answers back and cut the covered words.

The number of shards follows the bytes of text (``SHARD_BYTES`` each), so a shard doesn't
grow with the table.  What it gets of a passage grows with the number of chunks, not of
documents, that hold it, and shards are hash-dealt, so hot passages don't gather.  Words
are compared by 48 bits of their hashes.

Edge cases: null text has no words; rows of null id keep all words and count as nobody's
original; rows of one id never remove each other's words; documents shorter than a window
are kept whole; other columns travel as they are, beside the text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, MapType, StructField, StructType

from . import common as C
from .fm_index import FMIndex

CHUNK_BYTES = 6 << 20
SHARD_BYTES = 4 << 20  # of text for each shard, about
TASKS = 32_768  # of a stage, at most; a task takes its shards one by one
WINDOWS = (6, 200)  # words of a window, least and most
RUN = 6  # words of an anchor
ANCHOR = 5  # bytes of an anchor's hash that a shard compares
WORD = 6  # bytes of a word's hash that a shard compares

_PACKED = "chunk long, bytes long, ids array<long>, sizes array<int>, z binary, rest binary"


def _carried(parts: list[pa.Array]) -> bytes | None:
    """Rows of the other columns, in Arrow's own format."""
    if not parts or pa.types.is_null(parts[0].type):
        return None
    sink = pa.BufferOutputStream()
    rows = pa.record_batch([pa.concat_arrays(parts)], names=["rest"])
    with pa.ipc.new_stream(sink, rows.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(rows)
    return sink.getvalue().to_pybytes()


def _uncarried(blob: bytes) -> pa.Array:
    rows = pa.concat_arrays(pa.ipc.open_stream(blob).read_all().column("rest").chunks)
    return rows.cast(_relaxed(rows.type))


def _relaxed(kind: pa.DataType) -> pa.DataType:
    """The type with nulls allowed everywhere, as ``_nullable`` gives it for Spark."""
    if pa.types.is_struct(kind):
        return pa.struct([pa.field(f.name, _relaxed(f.type)) for f in kind])
    if pa.types.is_map(kind):
        return pa.map_(_relaxed(kind.key_type), pa.field(kind.item_field.name, _relaxed(kind.item_type)))
    if pa.types.is_list(kind):
        return pa.list_(pa.field(kind.value_field.name, _relaxed(kind.value_type)))
    return kind


def _nullable(kind):
    if isinstance(kind, StructType):
        return StructType([StructField(f.name, _nullable(f.dataType)) for f in kind.fields])
    if isinstance(kind, MapType):
        return MapType(_nullable(kind.keyType), _nullable(kind.valueType))
    return ArrayType(_nullable(kind.elementType)) if isinstance(kind, ArrayType) else kind


def _pack(batches):
    part = TaskContext.get().partitionId()
    z, seq = zstandard.ZstdCompressor(level=3), 0
    ids, texts, rest, total = [], [], [], 0

    def row():
        cols = [[(part << 32) + seq], [total], [ids], [[len(t) for t in texts]], [z.compress(b"".join(texts))], [_carried(rest)]]
        types = [pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.binary(), pa.binary()]
        return pa.record_batch([pa.array(c, t) for c, t in zip(cols, types)], names=["chunk", "bytes", "ids", "sizes", "z", "rest"])

    for batch in batches:
        since = 0
        for k, (i, t) in enumerate(zip(batch.column("doc_id").to_pylist(), batch.column("text"))):
            t = C.encoded(t.as_py())
            if ids and total + len(t) > CHUNK_BYTES:
                rest.append(batch.column("rest").slice(since, k - since))
                yield row()
                ids, texts, rest, total, seq, since = [], [], [], 0, seq + 1, k
            ids.append(i)
            texts.append(t)
            total += len(t)
        rest.append(batch.column("rest").slice(since))
    if ids:
        yield row()


def narrow(a: np.ndarray, n: int) -> bytes:
    """The low n bytes of each 64-bit number."""
    return np.ascontiguousarray(a.view(np.uint8).reshape(-1, 8)[:, :n]).tobytes()


def widen(raw: bytes, n: int) -> np.ndarray:
    out = np.zeros((len(raw) // n, 8), np.uint8)
    out[:, :n] = np.frombuffer(raw, np.uint8).reshape(-1, n)
    return out.view(np.uint64).reshape(-1)


def _texts(sizes: list[int], blob: bytes) -> list[bytes]:
    raw = zstandard.ZstdDecompressor().decompress(blob) if sum(sizes) else b""
    cut = np.cumsum([0, *sizes])
    return [raw[a:b] for a, b in zip(cut[:-1], cut[1:])]


class _Stretches:
    """Stretches of consecutive windows of one document with a common anchor.

    ``at``/``size``: first word and number of words; ``doc``: place of the document in the
    chunk; ``anchor``: its hash; ``key``: a hash of the words."""

    def __init__(self, words: list[np.ndarray], usable: list[bool], window: int):
        self.h = np.concatenate(words) if words else np.zeros(0, np.uint64)
        size = np.array([len(w) for w in words], np.int64)
        first = np.concatenate([[0], np.cumsum(size)[:-1]]) if len(size) else size
        ok = (size >= window) & np.array(usable, bool)
        count = np.where(ok, size - window + 1, 0)
        doc = np.repeat(np.arange(len(size)), count)
        at = np.repeat(first - (np.cumsum(count) - count), count) + np.arange(count.sum())
        width = window - RUN + 1
        if not len(at):
            self.at = self.size = self.doc = np.zeros(0, np.int64)
            self.anchor = self.key = np.zeros(0, np.uint64)
            return
        g = C.window_hashes(self.h, RUN)
        m = len(g) - width + 1
        low = g[:m].copy()
        for j in range(1, width):
            np.minimum(low, g[j : j + m], out=low)
        place = np.zeros(m, np.int16)
        for j in range(width - 1, -1, -1):
            place[g[j : j + m] == low] = j
        spot, low = at + place[at], low[at]
        new = np.concatenate([[True], (spot[1:] != spot[:-1]) | (at[1:] != at[:-1] + 1) | (doc[1:] != doc[:-1])])
        head = np.flatnonzero(new)
        self.at, self.doc = at[head], doc[head]
        self.size = np.diff(np.concatenate([head, [len(at)]])) + window - 1
        self.anchor = C.mix64(low[head])
        self.key = stretch_keys(self.h, self.at, self.size)

    def words(self, which: np.ndarray) -> np.ndarray:
        size = self.size[which]
        start = np.repeat(self.at[which] - (np.cumsum(size) - size), size)
        return self.h[start + np.arange(size.sum())]


_PLACE = C.stream64(512, 31) | np.uint64(1)
_WORD_BITS = np.uint64((1 << 8 * WORD) - 1)


def _chunk(ids, sizes, blob, window: int) -> tuple[_Stretches, list[np.ndarray], list[bytes]]:
    texts, words = _texts(sizes, blob), []
    for a, b in C.runs(sizes):
        w = C.Words(texts[a:b])
        h = w.hashes() & _WORD_BITS
        words += [h[p:q] for p, q in zip(w.ptr[:-1], w.ptr[1:])]
    return _Stretches(words, [i is not None for i in ids], window), words, texts


def _rows(table):
    for i in range(table.num_rows):
        yield [table.column(c)[i].as_py() for c in table.column_names]


def _anchors(window: int, shards: int):
    def run(batches):
        for batch in batches:
            for chunk, ids, sizes, blob, *_ in _rows(batch):
                s, _, _ = _chunk(ids, sizes, blob, window)
                order = np.lexsort((s.doc, s.anchor))
                a, d = s.anchor[order], s.doc[order]
                head = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]])) if len(a) else np.zeros(0, np.int64)
                tail = np.concatenate([head[1:], [len(a)]])[: len(head)] - 1
                many = d[head] != d[tail]
                a = a[head]
                shard = (a % np.uint64(shards)).astype(np.int64)
                order = np.argsort(shard, kind="stable")
                a, many, shard = a[order], many[order], shard[order]
                cut = np.searchsorted(shard, np.arange(shards + 1))
                live = [(k, x, y) for k, x, y in zip(range(shards), cut[:-1], cut[1:]) if y > x]
                yield pa.record_batch([pa.array([k for k, _, _ in live], pa.int64()), pa.array([chunk] * len(live), pa.int64()), pa.array([narrow(a[x:y] >> _CUT, ANCHOR) for _, x, y in live], pa.binary()), pa.array([many[x:y].tobytes() for _, x, y in live], pa.binary())], names=["shard", "chunk", "anchors", "many"])

    return run


_CUT = np.uint64(64 - 8 * ANCHOR)
_LOW = (1 << (64 - 8 * ANCHOR)) - 1
_REPEATED = pa.schema([("chunk", pa.int64()), ("shard", pa.int64()), ("anchors", pa.binary())])


def _repeated(table):
    """The anchors that several documents have, told to each chunk that has them."""
    chunks = table.column("chunk").to_pylist()
    each = [widen(x, ANCHOR) for x in table.column("anchors").to_pylist()]
    many = np.concatenate([np.frombuffer(x, bool) for x in table.column("many").to_pylist()])
    a = np.concatenate(each)
    value, back, count = np.unique(a, return_inverse=True, return_counts=True)
    good = count > 1
    good[back[many]] = True
    shard = table.column("shard")[0].as_py()
    keep, out, at = good[back], ([], [], []), 0
    for c, x in zip(chunks, each):
        k = keep[at : at + len(x)]
        at += len(x)
        if k.any():
            out[0].append(c)
            out[1].append(shard)
            out[2].append(narrow(x[k], ANCHOR))
    return pa.table([pa.array(o, f.type) for o, f in zip(out, _REPEATED)], schema=_REPEATED)


_SENT = pa.schema([("shard", pa.int64()), ("chunk", pa.int64()), ("sizes", pa.binary()), ("words", pa.binary()), ("low", pa.binary()), ("high", pa.binary())])


def _coded(words: np.ndarray) -> bytes:
    value, code = np.unique(words, return_inverse=True)
    kind = np.uint16 if len(value) < 1 << 16 else np.uint32
    return zstandard.ZstdCompressor(level=1).compress(np.int64(len(value)).tobytes() + narrow(value, WORD) + code.astype(kind).tobytes())


def _decoded(blob: bytes) -> np.ndarray:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    value = widen(raw[8 : 8 + WORD * n], WORD)
    return value[np.frombuffer(raw, np.uint16 if n < 1 << 16 else np.uint32, -1, 8 + WORD * n)]


def _squeezed(ids: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(ids.view(np.uint8).reshape(-1, 8).T).tobytes())


def _unsqueezed(blob: bytes) -> np.ndarray:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8)
    return np.ascontiguousarray(raw.reshape(8, -1).T).view(np.int64).reshape(-1)


def stretch_keys(words: np.ndarray, at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """A hash of the words at:at + size of each stretch (of the bytes that shards get)."""
    key = np.zeros(len(at), np.uint64)
    for j in range(int(size.max(initial=0))):
        live = size > j
        key[live] += C.mix64(words[at[live] + j]) * _PLACE[j]
    return C.mix64(key ^ size.astype(np.uint64))


def _send(window: int, shards: int):
    def run(packed, answers):
        known = [widen(x, ANCHOR) << _CUT | np.uint64(k & _LOW) for x, k in zip(answers.column("anchors").to_pylist(), answers.column("shard").to_pylist())]
        known = np.sort(np.concatenate(known)) if known else np.zeros(0, np.uint64)
        out = [[] for _ in _SENT]
        if len(known):
            for chunk, ids, sizes, blob, *_ in _rows(packed):
                s, _, _ = _chunk(ids, sizes, blob, window)
                look = (s.anchor >> _CUT) << _CUT | (s.anchor % np.uint64(shards)) & np.uint64(_LOW)
                which = np.flatnonzero(known[np.minimum(np.searchsorted(known, look), len(known) - 1)] == look)
                ident = np.array([0 if i is None else i for i in ids], np.int64)[s.doc[which]]
                order = np.lexsort((ident, s.key[which]))
                which, ident = which[order], ident[order]
                key = s.key[which]
                head = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
                tail = np.concatenate([head[1:], [len(key)]])[: len(head)] - 1
                low, high, which = ident[head], ident[tail], which[head]
                shard = (s.anchor[which] % np.uint64(shards)).astype(np.int64)
                order = np.argsort(shard, kind="stable")
                cut = np.searchsorted(shard[order], np.arange(shards + 1))
                for k in np.unique(shard):
                    x = order[cut[k] : cut[k + 1]]
                    w = which[x]
                    for c, v in zip(out, (int(k), chunk, s.size[w].astype(np.uint16).tobytes(), _coded(s.words(w)), _squeezed(low[x]), _squeezed(high[x]))):
                        c.append(v)
        return pa.table([pa.array(c, f.type) for c, f in zip(out, _SENT)], schema=_SENT)

    return run


_ANSWER = pa.schema([("chunk", pa.int64()), ("keys", pa.binary()), ("counts", pa.binary()), ("least", pa.binary())])


_NOBODY = np.iinfo(np.int64).max


def _gathered(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The places start:start + size of all stretches, one behind the other."""
    return np.repeat(start - (np.cumsum(size) - size), size) + np.arange(size.sum())


def _roles(words: np.ndarray, size: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which stretches are indexed and which are searched: by the first and last document
    that have their anchor."""
    start = np.cumsum(size) - size
    runs = size - RUN + 1
    anchor = np.minimum.reduceat(C.window_hashes(words, RUN)[_gathered(start, runs)], np.cumsum(runs) - runs)
    _, back = np.unique(anchor, return_inverse=True)
    first, last = np.full(len(size), _NOBODY), np.full(len(size), -_NOBODY - 1)
    np.minimum.at(first, back, low)
    np.maximum.at(last, back, high)
    return low < last[back], high > first[back]


def earliest(words: np.ndarray, size: np.ndarray, low: np.ndarray, high: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """For each window of the distinct stretches (of least and greatest documents low, high)
    the least document that an index of the earlier documents' stretches gives, and which
    stretches were searched."""
    own, asked = _roles(words, size, low, high)
    start, count = np.cumsum(size) - size, size - window + 1
    base = np.cumsum(count) - count
    result = np.full(count.sum(), _NOBODY)
    if not own.any() or not asked.any():
        return result, asked
    held = words[_gathered(start[own], size[own])]
    value, code = np.unique(held, return_inverse=True)
    index = FMIndex(code + 1, size[own], len(value), window, low[own])
    query = words[_gathered(start[asked], size[asked])]
    place = np.minimum(np.searchsorted(value, query), len(value) - 1)
    symbols = np.where(value[place] == query, place + 1, len(value) + 1)
    base = base[asked]
    for who, at, least, found in index.matches(symbols, size[asked]):
        result[base[who] + at] = np.where(found, least, _NOBODY)
    return result, asked


def _search(window: int):
    """Index a shard's earlier stretches, stream the later ones through the index."""

    def run(table):
        col = lambda c: table.column(c).to_pylist()
        chunks = col("chunk")
        sizes = [np.frombuffer(x, np.uint16).astype(np.int64) for x in col("sizes")]
        n = [len(x) for x in sizes]
        low = np.concatenate([_unsqueezed(x) for x in col("low")])
        high = np.concatenate([_unsqueezed(x) for x in col("high")])
        size = np.concatenate(sizes)
        words = np.concatenate([_decoded(x) for x in col("words")])
        start = np.cumsum(size) - size
        key = stretch_keys(words, start, size)
        _, first, back = np.unique(key, return_index=True, return_inverse=True)
        own = size[first]
        words = words[_gathered(start[first], own)]
        least_of, last_of = np.full(len(first), _NOBODY), np.full(len(first), -_NOBODY - 1)
        np.minimum.at(least_of, back, low)
        np.maximum.at(last_of, back, high)
        result, asked = earliest(words, own, least_of, last_of, window)
        count = own - window + 1
        base = np.cumsum(count) - count
        best = np.minimum.reduceat(result, base)
        tell = asked[back] & (best[back] < high)
        out, at = [[] for _ in _ANSWER], 0
        for c, m in zip(chunks, n):
            x = np.flatnonzero(tell[at : at + m]) + at
            at += m
            if len(x):
                p = back[x]
                rows = result[_gathered(base[p], count[p])]
                for o, v in zip(out, (c, key[x].tobytes(), count[p].astype(np.uint16).tobytes(), zstandard.compress(rows.tobytes(), 1))):
                    o.append(v)
        return pa.table([pa.array(o, f.type) for o, f in zip(out, _ANSWER)], schema=_ANSWER)

    return run


_SPANS = pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())]))


def spans(gone: np.ndarray) -> list[dict]:
    """The runs of removed words, as lo to hi - 1."""
    edge = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(np.int8), [0]])))
    return [{"lo": int(a), "hi": int(b)} for a, b in zip(edge[0::2], edge[1::2])]


def _cut(window: int, layout: bool):
    def run(packed, answers):
        keys, counts, least = (answers.column(c).to_pylist() for c in ("keys", "counts", "least"))
        key = np.concatenate([np.frombuffer(x, np.uint64) for x in keys]) if keys else np.zeros(0, np.uint64)
        count = np.concatenate([np.frombuffer(x, np.uint16) for x in counts]).astype(np.int64) if keys else np.zeros(0, np.int64)
        low = np.concatenate([np.frombuffer(zstandard.decompress(x), np.int64) for x in least]) if keys else np.zeros(0, np.int64)
        base = np.cumsum(count) - count
        order = np.argsort(key)
        out, carried = [[] for _ in range(5)], []
        for _, ids, sizes, blob, rest in _rows(packed):
            s, words, texts = _chunk(ids, sizes, blob, window)
            gone = np.zeros(len(s.h), bool)
            if len(key) and len(s.key):
                p = np.minimum(np.searchsorted(key, s.key, sorter=order), len(key) - 1)
                hit = np.flatnonzero(key[order[p]] == s.key)
                p, n = order[p[hit]], count[order[p[hit]]]
                inner = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                ident = np.array([0 if i is None else i for i in ids], np.int64)[s.doc[hit]]
                bad = low[np.repeat(base[p], n) + inner] < np.repeat(ident, n)
                at = (np.repeat(s.at[hit], n) + inner)[bad]
                change = np.zeros(len(s.h) + 1, np.int64)
                np.add.at(change, at, 1)
                np.add.at(change, at + window, -1)
                gone = np.cumsum(change)[:-1] > 0
            a = 0
            for i, w, t in zip(ids, words, texts):
                g = gone[a : a + len(w)]
                a += len(w)
                removed = int(g.sum())
                if layout and not removed:
                    kept = t
                else:
                    kept = b" ".join([x for x, y in zip(t.split(), g) if not y] if removed else t.split())
                kept = kept.decode("utf-8", "surrogatepass")
                for o, v in zip(out, (i, len(w), removed, kept, spans(g) if removed else [])):
                    o.append(v)
            if rest is not None:
                carried.append(_uncarried(rest))
        types = (pa.int64(), pa.int64(), pa.int64(), pa.string(), _SPANS)
        cols = [pa.array(o, t) for o, t in zip(out, types)]
        cols.append(pa.concat_arrays(carried) if carried else pa.nulls(len(out[0]), pa.string()))
        return pa.table(cols, names=["doc_id", "n_words", "n_removed", "kept", "spans", "rest"])

    return run


def remove_repeats(docs: DataFrame, window: int = 13, layout: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept, spans, rest) for each row of ``docs`` (doc_id, text).

    ``kept``: the words left, joined by one space; with ``layout`` a text that loses no
    word stays as it is.  ``spans``: the runs of removed words, as (lo, hi).  ``rest``: the
    other columns, as a struct (null where there are none)."""
    C.need(docs, "doc_id", "text")
    if not WINDOWS[0] <= window <= WINDOWS[1]:
        raise ValueError(f"window must lie between {WINDOWS[0]} and {WINDOWS[1]}")
    other = [F.col(f"`{c}`") for c in docs.columns if c not in ("doc_id", "text")]
    rest = F.struct(*other) if other else F.lit(None).cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), rest.alias("rest"))
    packed = C.materialize(rows.mapInArrow(_pack, _PACKED), "sub-packed")
    shards = max(1, -(-(packed.agg(F.sum("bytes")).collect()[0][0] or 0) // SHARD_BYTES))
    dealt = lambda df, key: df.repartition(min(shards, TASKS), key).groupBy(key)
    anchors = packed.select("chunk", "ids", "sizes", "z").mapInArrow(_anchors(window, shards), "shard long, chunk long, anchors binary, many binary")
    repeated = dealt(anchors, "shard").applyInArrow(_repeated, "chunk long, shard long, anchors binary")
    packed = dealt(packed.drop("bytes"), "chunk")  # one exchange serves both meetings
    sent = packed.cogroup(dealt(repeated, "chunk")).applyInArrow(_send(window, shards), "shard long, chunk long, sizes binary, words binary, low binary, high binary")
    answers = dealt(sent, "shard").applyInArrow(_search(window), "chunk long, keys binary, counts binary, least binary")
    kind = StructType().add("doc_id", "long").add("n_words", "long").add("n_removed", "long").add("kept", "string").add("spans", ArrayType(StructType().add("lo", "integer").add("hi", "integer"))).add("rest", _nullable(rows.schema["rest"].dataType))
    return packed.cogroup(dealt(answers, "chunk")).applyInArrow(_cut(window, layout), kind)


def without_repeats(docs: DataFrame, window: int = 13) -> DataFrame:
    """The rows of ``docs`` with repeated words cut from ``text`` (``n_chars``, where there
    is one, follows); rows that lose every word go."""
    out = remove_repeats(docs, window, layout=True).where("n_removed = 0 OR n_removed < n_words")
    field = lambda c: F.col("doc_id").cast(docs.schema[c].dataType) if c == "doc_id" else F.col("kept") if c == "text" else F.col("rest").getField(c)
    cols = {c: field(c) for c in docs.columns}
    if "n_chars" in cols:
        cols["n_chars"] = F.when(F.col("n_removed") > 0, F.length("kept")).otherwise(cols["n_chars"]).cast(docs.schema["n_chars"].dataType)
    return out.select(*[v.alias(c) for c, v in cols.items()])


def op2_substring_dedup(spark, sf_dir: str) -> DataFrame:
    with C.Scratch(spark) as tables:
        out = remove_repeats(C.read_table(spark, sf_dir, "documents", "doc_id", "text"), window=13)
        return tables.keep(out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256")), "sub-result")
