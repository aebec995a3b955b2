import random

import public_tokenizers
from tokenizers import Tokenizer

from curvetide.llm import token_counts as T

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_counts_equal_the_library():
    rng = random.Random(2)
    alphabet = "''''srtevmldXYab9٣éßñΣİẞ!?́-<|>中 \x85\t\n"
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 80))) for _ in range(3000)]
    texts += ["", "a<|endoftext|>b<|startoftext|>", "'''s 're'll", "=" * 3000, "ab" * 2000, " ".join(["word"] * 20000), "don't I'D we'LL 've"]
    tok = Tokenizer.from_file(PATH)
    assert T.Counter(PATH).count(texts) == [len(tok.encode(t, add_special_tokens=False).ids) for t in texts]


def test_chunk_maps_agree_with_one_pass():
    import numpy as np

    rng = np.random.default_rng(3)
    kind = rng.integers(0, T._CLASSES, 5 * T.CHUNK + 17).astype(np.uint8)
    table, state, want = T._machine(), 0, []
    for k in kind:
        want.append(state)
        state = int(table[int(k) * 8 + state])
    assert T.states_before(kind).tolist() == want


def merged(rules, symbols):
    """The plain merge loop, as a reference."""
    part = list(symbols)
    while True:
        ranks = [rules.rule.get(p, 1 << 30) for p in zip(part, part[1:])]
        if not ranks or min(ranks) == 1 << 30:
            return part
        i = ranks.index(min(ranks))
        part[i : i + 2] = [ranks[i]]


def spelled(rules, token):
    return [token] if token < 512 else spelled(rules, rules.parts[token][0]) + spelled(rules, rules.parts[token][1])


def test_which_tokens_stay_side_by_side():
    rng = random.Random(6)
    rules = T.Counter(PATH).machine.rules
    short = [t for t in range(97, 20_000) if t < 123 or 512 <= t and max(spelled(rules, t)) < 256]
    for _ in range(4000):
        t, u = rng.choice(short[:3000]), rng.choice(short)
        if all(merged(rules, spelled(rules, x)) == [x] for x in (t, u)):
            assert rules.stays(t, u) == (merged(rules, spelled(rules, t) + spelled(rules, u)) == [t, u]), (t, u)


def test_transducer_counts_prefixes():
    rng = random.Random(7)
    m = T.Counter(PATH).machine
    for _ in range(200):
        word = [ord(rng.choice("aehinrstx=")) for _ in range(rng.randint(1, 25))]
        state, total = 0, 0
        for k, c in enumerate(word):
            got = m._made(state, c)
            state, total = got >> 16, total + (got & 0xFFFF) - T._COUNT
            assert total == len(merged(m.rules, word[: k + 1]))
        assert total + (m._made(state, 256 + 97) & 0xFFFF) - T._COUNT == len(merged(m.rules, [*word, 256 + 97])) and m._made(state, 256 + 97) >> 16 == 0


def test_long_words_take_linear_time():
    import time

    rng = random.Random(1)
    counter, tok = T.Counter(PATH), Tokenizer.from_file(PATH)
    noise = "".join(rng.choice("etaoinshrdlu") for _ in range(3 * T.CHUNK + 5))
    for word in ("ab" * 1500, "=" * 2001, "x" * T.CHUNK, "abc" * T.CHUNK, noise, "don" + "'" * 1300 + "t"):
        for text in (word, "so " + word + " it is", word[:-1] + "\n" + word):
            assert counter.count([text, "a b"]) == [len(tok.encode(t, add_special_tokens=False).ids) for t in (text, "a b")]
    for word in ("x" * 1_000_000, "=" * 999_999, "".join(rng.choice("etaoinshrdlu") for _ in range(1_000_000))):
        since = time.time()
        n = counter.count([word])[0]
        assert 0 < n < len(word) and time.time() - since < 60


def test_states_are_dropped_between_batches(monkeypatch):
    monkeypatch.setattr(T, "STATES", 50)
    counter, tok = T.Counter(PATH), Tokenizer.from_file(PATH)
    for text in ("the first words of a text", "and others, with more states than fifty") * 2:
        assert counter.count([text]) == [len(tok.encode(text, add_special_tokens=False).ids)]
        assert len(counter.machine.state) <= 50


def test_other_files_are_refused(tmp_path):
    import json

    import pytest

    spec = json.load(open(PATH, encoding="utf-8"))
    for key, value in (("normalizer", None), ("pre_tokenizer", {"type": "Whitespace"}), ("model", spec["model"] | {"end_of_word_suffix": None}), ("model", spec["model"] | {"byte_fallback": True}), ("model", spec["model"] | {"merges": spec["model"]["merges"][::-1]})):
        with pytest.raises(ValueError):
            T.Rules(spec | {key: value})
    with pytest.raises(ValueError):
        T.Counter(public_tokenizers.path("byte_bpe_50k.json"))


def test_frames(docs):
    df = docs([(1, None), (2, ""), (3, "two words"), (3, "two words"), (None, "x" * 9000)]).withColumnRenamed("n_chars", "n_tokens")
    rows = sorted(T.token_counts(df, PATH, limit=1).collect(), key=str)
    got = {(r["doc_id"], r["n_bytes"], r["n_tokens"] > 0, r["over_limit"]) for r in rows}
    assert {(1, 0, False, False), (2, 0, False, False), (3, 9, True, True)} < got and len(rows) == 5
    assert T.token_counts(docs([]), PATH).count() == 0
