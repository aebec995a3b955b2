"""Token counts by finite-state transducers compiled from a tokenizer file.

``Counter`` reads a byte-level BPE tokenizer (NFC, lower case, word pieces, word ends) and
compiles two deterministic machines:

* the piece machine: states and character classes of the splitting pattern;
* the count transducer, over the bytes of pieces (a piece's last byte is a symbol of its
  own).  Its transitions carry token counts: the tokens of what was read so far change by
  the transition's number, and their sum over a text is the text's number of tokens.

A state of the count transducer knows, for each place from which a token may still reach
beyond the last byte, the trie node of the bytes since, the last token before that place,
and the count there relative to the present one.  That is all that the future depends on:
of the tokens that end at the next byte exactly one may follow the last token before it, as
BPE leaves the two side by side (``Rules.stays``).  So states look back no further than the
longest token, a byte costs one transition however long the word, and no merge loop runs.
Transitions are determinised from the trie and the merges when they are first taken, and
kept in a hash table; it is emptied between batches when it holds over ``STATES`` states.

Both machines read a text in chunks, all at once.  For the piece machine the map from start
state to end state is computed for all states of each chunk; the count transducer is back
in its first state behind each piece, so chunks start at pieces, and only chunks that
start inside a longer piece are read from further states: those in which the chunk before
ends.  Maps are composed by a parallel prefix scan, which gives each chunk its true start.

Special strings inside a text count one token each and split the text, as the library does
by default.  Files with other normalisers, splitters or model settings are refused.

Edge cases: null and empty texts have no tokens; white space has none; repeated rows are
counted each; other columns aren't read.
"""

from __future__ import annotations

import json
import re
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

CHUNK = 512  # characters of a chunk
STATES = 200_000  # of the count transducer that a Python worker keeps between batches
BATCH = 1 << 20

# ------------------------------------------------------------------ the piece machine
# Fixed values of the splitting pattern: contractions, letter runs, single numbers, runs
# of other characters; white space splits.
CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")
_BLANK, _OTHER, _NUMBER, _QUOTE, _LETTER = range(5)
_SPECIAL = {c: 5 + i for i, c in enumerate("stmdrevl")}
_CLASSES = 5 + len(_SPECIAL)
_FREE, _RUN, _SIGNS, _OPEN = range(4)  # between pieces, in letters, in signs, after a quote
_PREFIX = {c: 4 + i for i, c in enumerate("rvl")}  # a quote and a letter that needs another
_STATES = 4 + len(_PREFIX)


@lru_cache(1)
def _class_table() -> np.ndarray:
    out = np.full(0x110000, _OTHER, np.uint8)
    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    for pattern, kind in ((r"\p{L}", _LETTER), (r"\p{N}", _NUMBER), (r"\s", _BLANK)):
        hit = np.frombuffer("".join(regex.findall(pattern, every)).encode("utf-32-le"), np.uint32)
        out[hit] = kind
    out[ord("'")] = _QUOTE
    for c, kind in _SPECIAL.items():
        out[ord(c)] = kind
    return out


@lru_cache(1)
def _machine() -> np.ndarray:
    """next state = table[class * 8 + state]"""
    table = np.zeros((_CLASSES, 8), np.uint8)
    name = {v: k for k, v in _SPECIAL.items()}
    for kind in range(_CLASSES):
        for state in range(_STATES):
            if kind in (_BLANK, _NUMBER):
                to = _FREE
            elif kind == _OTHER:
                to = _SIGNS
            elif kind == _QUOTE:
                to = _SIGNS if state in (_SIGNS, _OPEN) else _OPEN
            else:
                to = _RUN
                c = name.get(kind, "")
                if state == _OPEN:
                    to = _FREE if c in CONTRACTIONS else _PREFIX.get(c, _RUN)
                elif state >= 4:
                    begun = next(k for k, v in _PREFIX.items() if v == state)
                    to = _FREE if begun + c in CONTRACTIONS else _RUN
            table[kind, state] = to
    return table.reshape(-1)


def prefix_scan(maps: np.ndarray, sums: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Compose the chunks' maps (states, chunks), adding up their sums: column k of the
    result leads from the start of the first chunk through chunk k."""
    apart = 1
    while apart < maps.shape[1]:
        first, later = maps[:, :-apart].copy(), maps[:, apart:]
        sums[:, apart:] = sums[:, :-apart] + np.take_along_axis(sums[:, apart:], first, axis=0)
        maps[:, apart:] = np.take_along_axis(later, first, axis=0)
        apart *= 2
    return maps, sums


def states_before(kind: np.ndarray) -> np.ndarray:
    """The machine's state before each character, by chunk maps and a prefix scan."""
    n, table = len(kind), _machine()
    lanes = max(1, -(-n // CHUNK))
    padded = np.zeros(lanes * CHUNK, np.uint8)
    padded[:n] = kind
    steps = np.ascontiguousarray(padded.reshape(lanes, CHUNK).T).astype(np.int16) * 8
    maps = np.repeat(np.arange(_STATES, dtype=np.int16)[:, None], lanes, axis=1)
    for row in steps:
        maps = table[row + maps].astype(np.int16)
    maps, _ = prefix_scan(maps, np.zeros_like(maps))
    state = np.concatenate([[_FREE], maps[_FREE, :-1]]).astype(np.int16)
    out = np.empty((CHUNK, lanes), np.uint8)
    for j, row in enumerate(steps):
        out[j] = state
        state = table[row + state].astype(np.int16)
    return out.T.reshape(-1)[:n]


def piece_starts(kind: np.ndarray) -> np.ndarray:
    """Where pieces start."""
    before = states_before(kind)
    nxt = np.concatenate([kind[1:], [_BLANK]]).astype(np.uint8)
    letter = kind >= _LETTER
    start = (kind == _NUMBER) | ((kind == _OTHER) | (kind == _QUOTE)) & (before != _SIGNS) & (before != _OPEN)
    start |= letter & ((before == _FREE) | (before == _SIGNS))
    closed = np.zeros(len(kind), bool)  # a letter that belongs to a contraction
    for c in CONTRACTIONS:
        hit = kind == _SPECIAL[c[0]]
        closed |= hit if len(c) == 1 else hit & (nxt == _SPECIAL[c[1]])
    return start | letter & (before == _OPEN) & ~closed


# ------------------------------------------------------------------ the count transducer
def _byte_names() -> list[str]:
    """The printable stand-ins of the 256 bytes in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    names = {b: chr(b) for b in plain}
    for i, b in enumerate(b for b in range(256) if b not in names):
        names[b] = chr(256 + i)
    return [names[b] for b in range(256)]


#: What a file must say for the machines to fit it.
PATTERN = "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
SPLITTER = {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": PATTERN}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]}
MODEL = {"type": "BPE", "dropout": None, "continuing_subword_prefix": None, "fuse_unk": False, "byte_fallback": False, "ignore_merges": False}
_PLAIN = {"single_word": False, "lstrip": False, "rstrip": False, "normalized": False, "special": True}


class Rules:
    """Tokens as numbers: 512 symbols (bytes, and bytes that end a piece), then the token of
    each merge in order.  ``parts``: the two tokens that a merge joins."""

    def __init__(self, spec: dict):
        model = spec["model"]
        other = [k for k, v in MODEL.items() if model.get(k) != v] + [k for k, v in (("normalizer", NORMALIZER), ("pre_tokenizer", SPLITTER)) if spec.get(k) != v]
        other += [t["content"] for t in spec["added_tokens"] if any(t[k] != v for k, v in _PLAIN.items())]
        end = model.get("end_of_word_suffix")
        if other or not end:
            raise ValueError(f"not a file that this machine fits: {other or 'end_of_word_suffix'}")
        names = _byte_names()
        number = {n: i for i, n in enumerate([*names, *(n + end for n in names)])}
        if any(n not in model["vocab"] for n in number):
            raise ValueError("the vocabulary lacks single bytes")
        self.parts: list[tuple[int, int]] = [(-1, -1)] * 512
        self.rule: dict[tuple[int, int], int] = {}
        for merge in model["merges"]:
            a, b = merge if isinstance(merge, list) else merge.split(" ")
            if a not in number or b not in number or a + b in number or a + b not in model["vocab"]:
                raise ValueError(f"merge {merge} isn't in order")
            pair = number[a], number[b]
            number[a + b] = self.rule[pair] = len(self.parts)
            self.parts.append(pair)
        self._known: dict[tuple[int, int], bool] = {}

    def _spine(self, token: int, side: int) -> list[int]:
        """The tokens at a token's left (0) or right (1) edge, from its symbol up."""
        out = [token]
        while out[-1] >= 512:
            out.append(self.parts[out[-1]][side])
        return out[::-1]

    def stays(self, t: int, u: int, below: int | None = None) -> bool:
        """Whether BPE leaves t and u side by side: no merge (earlier than ``below``) joins
        the tokens at their edges while both are there.  Later tokens have later merges; of
        merges of one rank the left one comes first."""
        none = len(self.parts)
        limit = none if below is None else below
        left, right = self._spine(t, 1), self._spine(u, 0)
        i = j = 0
        while True:
            up = left[i + 1] if i + 1 < len(left) else none
            down = right[j + 1] if j + 1 < len(right) else none
            joined = self.rule.get((left[i], right[j]), none)
            if joined < up and joined <= down and joined < limit:
                return False
            if up == down == none or min(up, down) >= limit:
                return True
            if up <= down:
                i += 1
            else:
                j += 1

    def follows(self, t: int, u: int) -> bool:
        known = self._known.get((t, u))
        if known is None:
            known = self._known[t, u] = self.stays(t, u)
        return known


_NODE, _COUNT = 40, 1 << 15  # a part of a state: trie node, last token + 1, relative count


class Transducer:
    """States are tuples of parts, by place; the first one has read nothing."""

    def __init__(self, rules: Rules):
        self.rules = rules
        spelled: list[tuple[int, ...] | None] = [(i,) for i in range(512)]
        for token in range(512, len(rules.parts)):
            a, b = rules.parts[token]
            whole = spelled[a] is not None and spelled[b] is not None and rules.stays(a, b, token)
            spelled.append(spelled[a] + spelled[b] if whole else None)  # None: never emitted
        self.child: dict[int, int] = {}
        self.token, self.open = [-1], [True]
        for token, text in enumerate(spelled):
            node = 0
            for symbol in text or ():
                self.open[node] = True
                nxt = self.child.get(node << 9 | symbol)
                if nxt is None:
                    nxt = self.child[node << 9 | symbol] = len(self.token)
                    self.token.append(-1)
                    self.open.append(False)
                node = nxt
            if text:
                self.token[node] = token
        self.clear()

    def clear(self) -> None:
        self.rules._known.clear()
        self.state: list[tuple[int, ...]] = [(_COUNT,)]
        self.number = {self.state[0]: 0}
        self._resize(16)

    def _resize(self, bits: int) -> None:
        old = getattr(self, "key", np.zeros(0, np.int64)), getattr(self, "value", np.zeros(0, np.int64))
        self.bits, self.key, self.value, self.used = bits, np.full(1 << bits, -1, np.int64), np.zeros(1 << bits, np.int64), 0
        if bits > 16:
            live = old[0] >= 0
            self._insert(old[0][live], old[1][live])

    def _place(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def _insert(self, key: np.ndarray, value: np.ndarray) -> None:
        """Adds keys that aren't there yet."""
        self.used += len(key)
        if self.used > 1 << (self.bits - 1):
            self._resize(self.bits + 1)
            return self._insert(key, value)
        at = self._place(key)
        while len(key):
            free = self.key[at] < 0
            self.key[at[free]] = key[free]  # of several at one place the last one stays
            there = self.key[at] == key
            self.value[at[there]] = value[there]
            key, value, at = key[~there], value[~there], (at[~there] + 1) & ((1 << self.bits) - 1)

    def _find(self, key: np.ndarray) -> np.ndarray:
        """Values of keys; -1 where a key isn't there."""
        at = self._place(key)
        have = self.key[at]
        out = self.value[at]
        off = np.flatnonzero(have != key)
        while len(off):
            lost = have[off] < 0
            out[off[lost]] = -1
            off = off[~lost]
            at[off] = (at[off] + 1) & ((1 << self.bits) - 1)
            have[off] = self.key[at[off]]
            out[off] = self.value[at[off]]
            off = off[have[off] != key[off]]
        return out

    def _made(self, state: int, symbol: int) -> int:
        """The transition of a state on a symbol, as next state << 16 | count + 2^15."""
        emitted, last, parts = None, -1, []
        for part in self.state[state]:
            node = self.child.get((part >> _NODE) << 9 | symbol)
            if node is None:
                continue
            before, count = (part >> 16) & 0xFFFFFF, (part & 0xFFFF) - _COUNT
            token = self.token[node]
            if emitted is None and token >= 0 and (not before or self.rules.follows(before - 1, token)):
                emitted, last = count + 1, token
            if self.open[node]:
                parts.append((node, before, count))
        if symbol >= 256:
            return emitted + _COUNT
        new = (*(n << _NODE | b << 16 | (c - emitted + _COUNT) for n, b, c in parts), (last + 1) << 16 | _COUNT)
        number = self.number.get(new)
        if number is None:
            number = self.number[new] = len(self.state)
            self.state.append(new)
        return number << 16 | emitted + _COUNT

    def step(self, state: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        key = state << 9 | symbol
        out = self._find(key)
        lost = np.flatnonzero(out < 0)
        if len(lost):
            new = np.unique(key[lost])
            self._insert(new, np.array([self._made(k >> 9, k & 511) for k in new.tolist()], np.int64))
            out[lost] = self._find(key[lost])
        return out

    def read(self, symbols: np.ndarray, low: np.ndarray, size: np.ndarray, state: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Read the chunks low:low + size from their states in lockstep: end states and
        sums of counts; with ``counts`` the count of each symbol too."""
        order = np.argsort(-size, kind="stable")
        low, size, state = low[order], size[order], state[order].astype(np.int64)
        total = np.zeros(len(low), np.int64)
        live = np.searchsorted(-size, -np.arange(1, int(size.max(initial=0)) + 1), side="right")
        for j, n in enumerate(live):
            got = self.step(state[:n], symbols[low[:n] + j])
            state[:n] = got >> 16
            emitted = (got & 0xFFFF) - _COUNT
            total[:n] += emitted
            if counts is not None:
                counts[low[:n] + j] = emitted
        back = np.empty_like(order)
        back[order] = np.arange(len(order))
        return state[back], total[back]

    def counts(self, symbols: np.ndarray, start: np.ndarray) -> np.ndarray:
        """The count of each symbol of pieces one behind the other; start: where they start."""
        n = len(symbols)
        out = np.zeros(n, np.int64)
        if not n:
            return out
        mark = np.arange(0, n, CHUNK)
        at = start[np.searchsorted(start, mark, side="right") - 1]
        inside = at <= mark - CHUNK  # a chunk that starts inside a long piece
        low = np.where(inside, mark, at)
        size = np.diff(np.append(low, n))
        end, total = self.read(symbols, low, size, np.zeros(len(low), np.int64), out)
        if not inside.any():
            return out
        # start states that a chunk is read from: the first one, and what the chunk before ends in
        known: list[dict[int, tuple[int, int]]] = [{0: (int(e), int(t))} for e, t in zip(end, total)]
        kind = _same_chunks(symbols, low, size)
        read: dict[tuple[int, int], tuple[int, int]] = {}
        while True:
            todo = [(k + 1, e) for k in np.flatnonzero(inside[1:]).tolist() for e, _ in known[k].values() if e not in known[k + 1]]
            if not todo:
                break
            fresh = {(kind[k], e): k for k, e in todo if (kind[k], e) not in read}
            which = np.array(list(fresh.values()), np.int64)
            ends, sums = self.read(symbols, low[which], size[which], np.array([e for _, e in fresh], np.int64))
            read |= {key: (int(e), int(t)) for key, e, t in zip(fresh, ends, sums)}
            for k, e in todo:
                known[k][e] = read[kind[k], e]
        most = max(len(m) for m in known)
        place = [{s: i for i, s in enumerate(m)} for m in known] + [{}]
        maps, sums = np.zeros((most, len(known)), np.int64), np.zeros((most, len(known)), np.int64)
        for k, m in enumerate(known):
            for i, (e, t) in enumerate(m.values()):
                maps[i, k], sums[i, k] = place[k + 1].get(e, 0), t
        maps, _ = prefix_scan(maps, sums)
        true = np.array([0, *([*m][i] for m, i in zip(known[1:], maps[0, :-1]))])
        again = np.flatnonzero(true != 0)
        self.read(symbols, low[again], size[again], true[again], out)
        return out


def _same_chunks(symbols: np.ndarray, low: np.ndarray, size: np.ndarray) -> list[bytes]:
    return [symbols[a : a + n].tobytes() for a, n in zip(low.tolist(), size.tolist())]


class Counter:
    def __init__(self, path: str):
        spec = json.load(open(path, encoding="utf-8"))
        self.machine = Transducer(Rules(spec))
        special = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.special = re.compile("|".join(map(re.escape, special))) if special else None

    def count(self, texts: list[str]) -> list[int]:
        """Token counts of texts."""
        extra, clean = [], []
        for t in texts:
            parts = self.special.split(t) if self.special else [t]
            extra.append(len(parts) - 1)
            clean.append("\n".join(_folded(p) for p in parts))
        text = "\n".join(clean) + "\n"
        code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        kind = _class_table()[code]
        start = np.flatnonzero(piece_starts(kind))
        if not len(start):
            return extra
        size = 1 + (code >= 0x80).astype(np.int64) + (code >= 0x800) + (code >= 0x10000)
        blank = kind == _BLANK
        before = np.concatenate([[0], np.cumsum(np.where(blank, 0, size))])  # symbols before a character
        symbols = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)[np.repeat(~blank, size)].astype(np.int64)
        start = before[start]
        symbols[np.append(start[1:], len(symbols)) - 1] += 256
        total = np.concatenate([[0], np.cumsum(self.machine.counts(symbols, start))])
        bounds = before[np.cumsum([0] + [len(t) + 1 for t in clean])]
        if len(self.machine.state) > STATES:
            self.machine.clear()
        return (total[bounds[1:]] - total[bounds[:-1]] + extra).tolist()


def _folded(text: str) -> str:
    if not text.isascii():
        if not unicodedata.is_normalized("NFC", text):
            text = unicodedata.normalize("NFC", text)
        text = text.replace("Σ", "σ")  # a capital sigma is lowered by itself
    return text.lower()


@lru_cache(4)
def compile_file(path: str) -> Counter:
    return Counter(path)


def _count(path: str, limit: int):
    def run(batches):
        machine = compile_file(path)
        for batch in batches:
            ids = batch.column("doc_id")
            for a, b, texts in C.text_batches(batch, limit=BATCH):
                n = machine.count([t.decode("utf-8", "surrogatepass") for t in texts])
                yield pa.record_batch([ids.slice(a, b - a), pa.array([len(t) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n])], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return run


def token_counts(docs: DataFrame, tokenizer: str, limit: int = 2048) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of each row (doc_id, text)."""
    C.need(docs, "doc_id", "text")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_count(tokenizer, limit), "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op7_token_counts(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(C.read_table(spark, sf_dir, "documents", "doc_id", "text"), public_tokenizers.path("word_bpe_49k.json"))
