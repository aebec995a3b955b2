"""SentencePiece models on the tokenizers library.

``read_model`` parses the model's protobuf; ``build`` makes a tokenizer of it: normaliser
(precompiled map, dummy prefix, blank removal), metaspace marker, unigram scores or BPE
merges, byte fallback, and the decoder.  Batches are encoded by the library's threads: as
many as a task has cores (``spark.task.cpus``), two at least.  ``parity`` compares ids with the
sentencepiece library: each worker runs it on fixed probes before it encodes anything, and
``digests`` on one of ``CHECK`` documents (by a hash of the text), whose result it returns;
the query does so on all documents.

If no piece of a BPE model has the marker behind another character, no merge crosses the
place before a marker, and the text may be split there first; this gives the same ids and
lets the library cache words.  Without normalisation besides the dummy prefix such a text is
encoded word by word: a batch's bytes are cut into words and these looked up as whole columns,
each distinct word once; each worker keeps the ids of up to ``KEPT`` words in one array (beyond
it, of the half that most batches had), and new words of a batch are joined to texts of ``JOIN``
words, which the library encodes without a split of its own; words begin where a piece with the
marker does.  Ids of a batch are one array until they are returned.

Edge cases: null and empty texts have no ids and decode to empty; text that the model's
normaliser changes isn't restored by decoding (``roundtrip`` tells); repeated rows are
encoded each; other columns are kept by ``encode`` and clash with none (the new ones
replace columns of their names).
"""

from __future__ import annotations

import hashlib
import os
import zlib
from functools import lru_cache
from itertools import chain, compress, count, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

MARK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # piece types of the format
UNIGRAM, BPE = 1, 2  # model types of the format
BATCH = 4 << 20
KEPT, LONG, JOIN = 1 << 19, 64, 200  # words whose ids are kept, their length at most, new ones encoded at once
CHECK = 8  # of so many documents one is encoded by the sentencepiece library too
#: Texts that every loaded model must encode as the sentencepiece library does.
PROBES = ["", " ", "a", "  two  blanks ", "Größe, ça va?", "tab\tline\nend", "中文 and 😀", "\x00\x7f", "<s> </s> <unk>", "1234.5", "▁mark▁", "x" * 300, "'s ''"]


# ------------------------------------------------------------------ protobuf
def _varint(raw: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        b = raw[at]
        at += 1
        value |= (b & 127) << shift
        shift += 7
        if b < 128:
            return value, at


def fields(raw: bytes):
    """(number, value) of a message's fields; bytes for length-delimited ones."""
    at = 0
    while at < len(raw):
        tag, at = _varint(raw, at)
        kind = tag & 7
        if kind == 0:
            value, at = _varint(raw, at)
        elif kind in (1, 5):
            n = 8 if kind == 1 else 4
            value, at = raw[at : at + n], at + n
        elif kind == 2:
            n, at = _varint(raw, at)
            value, at = raw[at : at + n], at + n
        else:
            raise ValueError(f"wire type {kind}")
        yield tag >> 3, value


def read_model(raw: bytes) -> dict:
    """pieces as (text, score, type), and the settings that encoding needs."""
    out = {"pieces": [], "type": UNIGRAM, "byte_fallback": False, "charsmap": b"", "dummy_prefix": True, "strip": True, "escape": True, "unk": 0, "suffix": False}
    for n, v in fields(raw):
        if n == 1:
            piece, score, kind = "", 0.0, NORMAL
            for k, x in fields(v):
                if k == 1:
                    piece = x.decode("utf-8")
                elif k == 2:
                    score = float(np.frombuffer(x, "<f4")[0])
                elif k == 3:
                    kind = x
            out["pieces"].append((piece, score, kind))
        elif n == 2:
            trainer = dict(fields(v))
            out["type"] = trainer.get(3, UNIGRAM)
            out["byte_fallback"] = bool(trainer.get(35, 0))
            out["suffix"] = bool(trainer.get(24, 0))
        elif n == 3:
            spec = dict(fields(v))
            out["charsmap"] = spec.get(2, b"")
            out["dummy_prefix"], out["strip"], out["escape"] = bool(spec.get(3, 1)), bool(spec.get(4, 1)), bool(spec.get(5, 1))
    out["unk"] = next((i for i, (_, _, k) in enumerate(out["pieces"]) if k == UNKNOWN), 0)
    return out


# ------------------------------------------------------------------ the tokenizer
def _merges(pieces: list[tuple[str, float, int]]) -> list[tuple[str, str]]:
    """All pairs of pieces that join to a piece, by the score of what they join to."""
    place = {p: i for i, (p, _, kind) in enumerate(pieces) if kind in (NORMAL, USER, UNUSED)}
    found = []
    for p, score, kind in pieces:
        if kind == NORMAL:
            for i in range(1, len(p)):
                if p[:i] in place and p[i:] in place:
                    found.append((-score, place[p], place[p[:i]], place[p[i:]], p[:i], p[i:]))
    found.sort()
    return [(a, b) for *_, a, b in found]


def build(model: dict):
    from tokenizers import AddedToken, Regex, Tokenizer, decoders, models, normalizers, pre_tokenizers

    pieces = model["pieces"]
    unk = pieces[model["unk"]][0]
    if model["suffix"] or not model["escape"]:
        raise ValueError("models with suffix markers or plain blanks aren't supported")
    if model["type"] == UNIGRAM:
        least = min((s for _, s, k in pieces if k == NORMAL), default=0.0)
        core = models.Unigram([(p, least - 10.0 if k != NORMAL and k != USER else s) for p, s, k in pieces], unk_id=model["unk"], byte_fallback=model["byte_fallback"])
    elif model["type"] == BPE:
        core = models.BPE({p: i for i, (p, _, _) in enumerate(pieces)}, _merges(pieces), unk_token=unk, fuse_unk=True, byte_fallback=model["byte_fallback"])
    else:
        raise ValueError("only unigram and BPE models are supported")
    tok = Tokenizer(core)
    steps = [normalizers.Precompiled(model["charsmap"])] if model["charsmap"] else []
    if model["strip"]:
        steps += [normalizers.Replace(Regex(" +"), " "), normalizers.Replace(Regex("^ | $"), "")]
    if model["dummy_prefix"]:
        steps.append(normalizers.Prepend(MARK))
    tok.normalizer = normalizers.Sequence([*steps, normalizers.Replace(" ", MARK)])
    if model["type"] == BPE and not any(MARK in p.lstrip(MARK) for p, _, _ in pieces):
        tok.pre_tokenizer = pre_tokenizers.Split(Regex(f"{MARK}*[^{MARK}]+|{MARK}+"), "isolated")
    user = [AddedToken(p, normalized=False) for p, _, k in pieces if k == USER]
    if user:
        tok.add_tokens(user)
    tok.decoder = decoders.Sequence([decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse(), *([decoders.Strip(" ", 1, 0)] if model["dummy_prefix"] else [])])
    return tok


def by_words(model: dict) -> bool:
    """Whether ids of a text are those of its words: no merge crosses the place before a
    marker, and nothing but the dummy prefix is normalised."""
    pieces = model["pieces"]
    if model["type"] != BPE or model["strip"] or model["charsmap"] or any(k == USER for _, _, k in pieces):
        return False
    return any(p == MARK and k == NORMAL for p, _, k in pieces) and not any(MARK in p.lstrip(MARK) for p, _, _ in pieces)


def _pick(pool: np.ndarray, first: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The stretches of ``pool`` one behind the other, and the places where each begins (and the last ends)."""
    ends = np.concatenate([[0], np.cumsum(size)])
    return pool[np.repeat(first - ends[:-1], size) + np.arange(ends[-1])], ends


def _joined(lists: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
    ends = np.cumsum([0, *map(len, lists)])
    return np.fromiter(chain.from_iterable(lists), np.int32, ends[-1]), ends


def _parts(flat, ends: np.ndarray) -> list:
    at = ends.tolist()
    return [flat[a:b] for a, b in zip(at, at[1:])]


class Codec:
    def __init__(self, path: str):
        self.path = path
        self.model = read_model(open(path, "rb").read())
        self.tok = build(self.model)
        self._bytes = self._library = self._bare = None
        if by_words(self.model):
            self._bare = build(self.model)
            self._bare.normalizer = self._bare.pre_tokenizer = None
            self._bare.model._resize_cache(0)  # no word comes twice
            self._starts = np.array([p.startswith(MARK) for p, _, _ in self.model["pieces"]])
            # a kept word's number n: its ids are pool[ends[n]:ends[n + 1]], hits[n] batches had it
            self._ids: dict[str, int] = {}
            self._pool, self._ends, self._hits = np.zeros(0, np.int32), np.zeros(1, np.int64), np.zeros(0, np.int64)

    def encode(self, texts: list[str]) -> list[list[int]]:
        return [x.tolist() for x in _parts(*self.flat([t.encode("utf-8") for t in texts]))]

    def flat(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of UTF-8 texts one behind the other, and the places where each text's begin
        (and the last ones end)."""
        if self._bare is None:
            return _joined([e.ids for e in self.tok.encode_batch_fast([t.decode("utf-8") for t in texts], add_special_tokens=False)])
        before = b" " if self.model["dummy_prefix"] else b""
        texts = [before + t.replace(MARK.encode(), b" ") if t else b"" for t in texts]
        bounds = np.cumsum([0, *map(len, texts)])
        buf = np.frombuffer(b"".join(texts), np.uint8)
        blank = buf == 32
        begins = blank.copy()  # a word is a run of blanks and the bytes up to the next one
        begins[1:] &= ~blank[:-1]
        begins[bounds[:-1][np.diff(bounds) > 0]] = True
        start = np.flatnonzero(begins)
        column = pa.LargeStringArray.from_buffers(len(start), pa.py_buffer(np.append(start, len(buf))), pa.py_buffer(buf)).dictionary_encode()
        words = column.dictionary.to_numpy(zero_copy_only=False).tolist()
        number = np.fromiter(map(self._ids.get, words, repeat(-1)), np.int64, len(words))
        unknown = np.flatnonzero(number < 0)
        new = [words[i] for i in unknown.tolist()]
        self._learn(new)
        number[unknown] = np.fromiter(map(self._ids.__getitem__, new), np.int64, len(new))
        self._hits[number] += 1
        number = number[column.indices.to_numpy()]
        first = self._ends[number]
        ids, ends = _pick(self._pool, first, self._ends[number + 1] - first)
        self._forget(sum(len(w) > LONG for w in new))
        return ids, ends[np.searchsorted(start, bounds)]

    def _learn(self, new: list[str]) -> None:
        """Adds the ids of new words, long ones last.  Those behind one marker are joined: a
        piece with the marker begins each; long ones and words behind none or several are
        encoded alone."""
        single = [w[0] == " " and w[1:2] not in ("", " ") and len(w) <= LONG for w in new]
        words = list(compress(new, single))
        texts = ["".join(words[i : i + JOIN]) for i in range(0, len(words), JOIN)]
        alone = sorted((w for w, s in zip(new, single) if not s), key=lambda w: len(w) > LONG)
        ids, ends = _joined([e.ids for e in self._bare.encode_batch_fast([w.replace(" ", MARK) for w in texts + alone], add_special_tokens=False)])
        cut = np.flatnonzero(self._starts[ids[: ends[len(texts)]]])
        if not np.array_equal(np.searchsorted(cut, ends[: len(texts) + 1]), np.minimum(np.arange(len(texts) + 1) * JOIN, len(words))):
            raise ValueError(f"{self.path}: {len(cut)} words of {len(words)} in joined texts")
        self._ids.update(zip(chain(words, alone), count(len(self._ids))))
        self._ends = np.concatenate([self._ends[:-1], self._ends[-1] + np.concatenate([cut, ends[len(texts) :]])])
        self._pool = np.concatenate([self._pool, ids])
        self._hits = np.concatenate([self._hits, np.zeros(len(new), np.int64)])

    def _forget(self, last: int) -> None:
        """Drops the last words learnt, and of more than ``KEPT`` all but the half of it that
        most batches had (of equals the newest)."""
        for _ in range(last):
            self._ids.popitem()
        n = len(self._ids)
        keep = slice(n)
        if n > KEPT:
            keep = np.sort(np.argsort(self._hits[:n], kind="stable")[n - KEPT // 2 :])
            self._hits //= 2
            left = np.zeros(n, bool)
            left[keep] = True
            self._ids = dict(zip(compress(self._ids, left.tolist()), count()))
        elif not last:
            return
        first, size = self._ends[:-1][keep], np.diff(self._ends)[keep]
        self._pool, self._ends = _pick(self._pool, first, size)
        self._hits = self._hits[keep]

    def decode(self, ids: list[list[int]]) -> list[str]:
        """The texts of id lists; joined bytes of the pieces, the dummy prefix cut."""
        return [x.decode("utf-8", "replace") for x in self.decode_flat(*_joined(ids))]

    def decode_flat(self, ids: np.ndarray, ends: np.ndarray) -> list[bytes]:
        """The bytes of the texts whose ids stand one behind the other."""
        if self._bytes is None:
            self._bytes = pa.array([b"" if k == CONTROL else bytes([int(p[3:5], 16)]) if k == BYTE else b" \xe2\x81\x87 " if k == UNKNOWN else p.replace(MARK, " ").encode() for p, _, k in self.model["pieces"]], pa.large_binary())
        found = self._bytes.take(pa.array(ids))
        _, at, data = found.buffers()
        out = _parts(data.to_pybytes() if data else b"", np.frombuffer(at, np.int64, len(ids) + 1, found.offset * 8)[ends])
        return [x[1:] if x[:1] == b" " else x for x in out] if self.model["dummy_prefix"] else out

    def parity(self, texts: list[str], ids: list | None = None) -> list[bool]:
        """Whether the sentencepiece library gives the same ids (lists or arrays)."""
        if self._library is None:
            import sentencepiece

            self._library = sentencepiece.SentencePieceProcessor(model_file=self.path)
        ids = self.encode(texts) if ids is None else ids
        return [np.array_equal(a, b) for a, b in zip(ids, self._library.encode(texts, return_type="numpy", num_threads=1))]


@lru_cache(2)
def load(path: str, threads: int = 2) -> Codec:
    """The codec of a worker; its first one sets the number of the library's threads."""
    os.environ.setdefault("RAYON_NUM_THREADS", str(threads))
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "true")
    codec = Codec(path)
    if not all(codec.parity(PROBES)):
        raise ValueError(f"{path}: the rebuilt tokenizer differs from sentencepiece")
    return codec


def task_threads(docs: DataFrame) -> int:
    return max(2, int(docs.sparkSession.conf.get("spark.task.cpus", "1")))


def encode(docs: DataFrame, path: str, threads: int | None = None) -> DataFrame:
    """``docs`` with ``ids`` (array of int) of the column ``text``."""
    C.need(docs, "text")
    threads = threads or task_threads(docs)
    rest = docs.drop("ids")
    names = [*rest.columns, "ids"]

    def run(batches):
        codec = load(path, threads)
        for batch in batches:
            for a, b, texts in C.text_batches(batch, limit=BATCH):
                ids, ends = codec.flat(texts)
                yield pa.record_batch([*batch.slice(a, b - a).columns, pa.ListArray.from_arrays(ends.astype(np.int32), ids)], names=names)

    return rest.mapInArrow(run, rest.select("*", F.array().cast("array<int>").alias("ids")).schema)


_DIGESTS = "doc_id long, n_bytes long, n_tokens long, ids_sha256 string, roundtrip boolean, parity boolean"


def _digests(path: str, threads: int, check: int):
    def run(batches):
        codec = load(path, threads)
        for batch in batches:
            doc = batch.column("doc_id")
            for a, b, raw in C.text_batches(batch, limit=BATCH):
                flat, ends = codec.flat(raw)
                back = codec.decode_flat(flat, ends)
                ids = _parts(flat.astype("<i4", copy=False), ends)
                digest = [hashlib.sha256(x).hexdigest() for x in ids]
                at = [i for i, t in enumerate(raw) if zlib.crc32(t) % check == 0]
                same = dict(zip(at, codec.parity([raw[i].decode("utf-8") for i in at], [ids[i] for i in at])))
                cols = [pa.array([len(t) for t in raw], pa.int64()), pa.array(np.diff(ends)), pa.array(digest), pa.array([x == y for x, y in zip(raw, back)]), pa.array([same.get(i) for i in range(len(raw))], pa.bool_())]
                yield pa.record_batch([doc.slice(a, b - a), *cols], names=[f.split()[0] for f in _DIGESTS.split(", ")])

    return run


def digests(docs: DataFrame, path: str, threads: int | None = None, check: int = CHECK) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, ids_sha256, roundtrip, parity): encoded, decoded, compared.

    ``parity`` is null for documents that aren't compared with the sentencepiece library;
    with ``check`` 1 all are."""
    C.need(docs, "doc_id", "text")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(_digests(path, threads or task_threads(docs), check), _DIGESTS)


def op1_sentencepiece(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digests(C.read_table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path("piece_bpe_32k.model"), check=1)
