import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from curvetide.llm import sentencepiece_codec as S

PATH = public_tokenizers.path("piece_bpe_32k.model")
TEXTS = ["", " ", "Hello  world", "Größe\tça\n中文 😀", "<s> </s> <0x41>", "a" * 5000, "x y " * 3000, "\x00\x01"]


def test_ids_equal_the_library():
    import sentencepiece

    codec = S.load(PATH)
    other = sentencepiece.SentencePieceProcessor(model_file=PATH)
    ids = codec.encode(TEXTS)
    assert ids == other.encode(TEXTS)
    assert codec.decode(ids) == other.decode(ids) == TEXTS
    assert [codec.tok.decode(x, skip_special_tokens=False) for x in ids] == TEXTS


def _varint(n):
    out = b""
    while True:
        out += bytes([n & 127 | (128 if n > 127 else 0)])
        n >>= 7
        if not n:
            return out


def _field(number, value):
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + np.float32(value).tobytes()
    return _varint(number << 3) + _varint(value)


def unigram_model():
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3)] + [(f"<0x{b:02X}>", -20.0, 6) for b in range(256)]
    pieces += [(p, s, 1) for p, s in (("▁", -2.0), ("a", -3.0), ("b", -3.1), ("ab", -3.5), ("▁a", -3.2), ("ba", -4.0), ("▁ab", -3.9), ("aba", -5.0))]
    raw = b"".join(_field(1, _field(1, p.encode()) + _field(2, s) + _field(3, k)) for p, s, k in pieces)
    raw += _field(2, _field(3, 1) + _field(35, 1))
    return raw + _field(3, _field(1, b"identity") + _field(3, 1) + _field(4, 0) + _field(5, 1))


def test_unigram_with_byte_fallback(tmp_path):
    import sentencepiece

    path = tmp_path / "u.model"
    path.write_bytes(unigram_model())
    model = S.read_model(path.read_bytes())
    assert model["type"] == S.UNIGRAM and model["byte_fallback"] and not model["strip"]
    tok = S.build(model)
    other = sentencepiece.SentencePieceProcessor(model_proto=path.read_bytes())
    texts = ["ab", "abab ba", " aba é", "c", "ab  ab", ""]
    assert [tok.encode(t, add_special_tokens=False).ids for t in texts] == other.encode(texts)


def test_frames(docs):
    df = docs([(1, "ab cd"), (2, None), (2, None), (None, "")]).withColumn("ids", F.lit("old"))
    rows = S.encode(df, PATH).collect()
    assert sorted(len(r["ids"]) for r in rows) == [0, 0, 0, len(S.load(PATH).encode(["ab cd"])[0])]
    assert rows[0].asDict().keys() >= {"doc_id", "lang", "n_chars", "ids"}
    out = S.digests(df, PATH).collect()
    assert all(r["roundtrip"] for r in out) and len(out) == 4
    assert S.digests(docs([]), PATH).count() == 0


def test_parity_is_returned(docs):
    df = docs([(i, f"text number {i} é") for i in range(60)] + [(60, None)])
    every = S.digests(df, PATH, check=1).collect()
    assert all(r["parity"] for r in every) and len(every) == 61
    some = {r["doc_id"]: r["parity"] for r in S.digests(df, PATH).collect()}
    assert set(some.values()) == {True, None} and some[60]
    codec = S.load(PATH)
    assert codec.parity(["a b", "c"], [codec.encode(["a b"])[0], [1]]) == [True, False]


def test_threads_of_a_task(spark, docs):
    def threads(batches):
        import os

        import pyarrow as pa

        S.load(PATH, 2)
        for batch in batches:
            yield pa.record_batch([pa.array([os.environ["RAYON_NUM_THREADS"]] * batch.num_rows)], names=["n"])

    assert S.task_threads(docs([])) == 2
    assert docs([(1, "a b")]).mapInArrow(threads, "n string").collect()[0]["n"] == "2"


def test_unsupported_models_are_refused():
    with pytest.raises(ValueError):
        S.build({**S.read_model(unigram_model()), "type": 3})


def test_the_query_compares_every_document(spark, sf):
    rows = S.op1_sentencepiece(spark, sf).collect()
    assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count() and all(r["parity"] for r in rows)


def test_words_are_encoded_once(monkeypatch):
    codec, seen = S.Codec(PATH), []
    learn = S.Codec._learn
    monkeypatch.setattr(S.Codec, "_learn", lambda self, new: (seen.append(sorted(new)), learn(self, new))[1])
    first = codec.encode(["one two one", "two three", "two  three "])
    assert codec.encode(["three one", "", " two"])[0] == codec.encode(["three"])[0] + codec.encode(["one"])[0]
    assert seen[0] == [" ", "  three", " one", " three", " two"] and seen[1:] == [["  two"], [], []]
    assert all(codec.parity(["one two one", "two three", "two  three "], first))


def test_words_equal_whole_texts(monkeypatch):
    """Fuzz with blanks, markers, bytes and long words, also when few words are kept."""
    rng = np.random.default_rng(5)
    parts = [" ", "  ", "   ", S.MARK, "\n", "\t", "word", "Wort", "中", "😀", "é", "\x00", "<s>", "<0x41>", "a" * 90, "'s", ",", "12"]
    texts = ["".join(rng.choice(parts, rng.integers(0, 12))) for _ in range(3000)]
    for kept in (S.KEPT, 40):
        monkeypatch.setattr(S, "KEPT", kept)
        codec = S.Codec(PATH)
        for lo in range(0, len(texts), 100):
            batch = texts[lo : lo + 100]
            assert all(codec.parity(batch))
            assert codec.encode(batch) == [e.ids for e in codec.tok.encode_batch_fast(batch, add_special_tokens=False)]
        assert len(codec._ids) <= kept and max(map(len, codec._ids)) <= S.LONG


def test_words_of_most_batches_stay_kept(monkeypatch):
    """Rare words that come first don't keep frequent ones out."""
    monkeypatch.setattr(S, "KEPT", 8)
    codec, seen = S.Codec(PATH), []
    learn = S.Codec._learn
    monkeypatch.setattr(S.Codec, "_learn", lambda self, new: (seen.extend(new), learn(self, new))[1])
    codec.encode([" ".join(f"rare{i}" for i in range(50))])
    for i in range(40):
        assert all(codec.parity([f"often again new{i} {'long' * 20}{i}", "often"]))
    assert seen.count(" often") == seen.count(" again") == 1
    assert len(codec._ids) <= 8 and len(codec._pool) == codec._ends[-1] < 100


@pytest.mark.parametrize("texts", [[], [""], ["", " ", "", "  "], ["a ", " b", "", S.MARK, "�", "é" * 99, "x  " * 500, ""], ["a" * 64, "a" * 65, " a" * 700]])
def test_flat_ids(texts):
    import sentencepiece

    codec = S.Codec(PATH)
    for _ in range(2):
        ids, ends = codec.flat([t.encode() for t in texts])
        assert [ids[a:b].tolist() for a, b in zip(ends, ends[1:])] == sentencepiece.SentencePieceProcessor(model_file=PATH).encode(texts)
        assert codec.decode_flat(ids, ends) == [t.replace(S.MARK, " ").encode() for t in texts] and len(ends) == len(texts) + 1
