import gzip
import hashlib
import io
import json
import zlib

import pytest
from pyarrow import fs as pafs

from curvetide.llm import common as C
from curvetide.llm import warc as W

SCHEMA = "page_id long, url string, html string, record_type string"


def test_pages_come_back(spark):
    big, other = "é<p>" * 400, "y" * 1000
    rows = [(1, "http://a/1", big, "x"), (5, "http://a/5", big, "x"), (3, None, big, None), (2, "u", "small", None), (4, "u", "small", None), (6, "u\r\nX: y", None, None), (None, "n", other, None), (7, "v", other, None), (7, "v", other, None), (8, "v", "", None)]
    uri = W._uri(C.fresh_path(spark, "warc-test"))
    got = W.read_archives(W.write_archives(spark.createDataFrame(rows, SCHEMA), uri, keep_whole=True), uri).collect()
    sha = lambda t: hashlib.sha1((t or "").encode()).hexdigest()
    want = [(1, big, "revisit", 5), (5, big, "response", None), (3, big, "revisit", 5), (2, "small", "response", None), (4, "small", "response", None), (6, None, "response", None), (None, other, "response", None), (7, other, "response", None), (7, other, "response", None), (8, "", "response", None)]
    want = sorted(((i, len((t or "").encode()), sha(t), k, r) for i, t, k, r in want), key=str)
    assert sorted(((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got), key=str) == want


def test_attempts_share_no_names(spark):
    """Two runs of the same tasks into one folder: manifests own their files; the rest goes."""
    df = spark.createDataFrame([(i, "u", f"page {i} " * 300, None) for i in range(8)], SCHEMA)
    uri = W._uri(C.fresh_path(spark, "warc-twice"))
    lost, kept = (W.write_archives(df, uri) for _ in range(2))
    paths = [{r["path"] for r in m.collect()} for m in (lost, kept)]
    assert not paths[0] & paths[1]
    assert W.sweep(kept, uri) == 2 * len(paths[0]) and W.sweep(kept, uri) == 0
    assert sorted(r["page_id"] for r in W.read_archives(kept, uri).collect()) == list(range(8))


def test_record_ids(spark):
    rows = [(1, "u", "a" * 2000, None), (1, "u", "b" * 2000, None), (2, "u", "a" * 2000, None)]
    uri = W._uri(C.fresh_path(spark, "warc-ids"))
    manifest = W.write_archives(spark.createDataFrame(rows, SCHEMA), uri).collect()
    heads = []
    for m in manifest:
        for raw in W.records(W.inflated(open(m["path"], "rb"))):
            heads.append(W.parse(raw)[0])
    heads = [h for h in heads if h["warc-type"] != "warcinfo"]
    ids = [h["warc-record-id"] for h in heads]
    assert len(set(ids)) == 3
    assert [h["warc-refers-to"] for h in heads if h["warc-type"] == "revisit"] == [i for i in ids if i.startswith("<urn:page:2:")]


def test_empty_table(spark):
    uri = W._uri(C.fresh_path(spark, "warc-none"))
    assert W.read_archives(W.write_archives(spark.createDataFrame([], SCHEMA), uri), uri).count() == 0


@pytest.mark.parametrize("members", [1, 3])
def test_normaliser(tmp_path, members):
    recs = [W.record("response", i, f"u{i}", "d", 6 + 1000 * i, b"a\r\n\r\nb" + b"z" * 1000 * i) for i in range(30)]
    parts = [b"".join(recs[k::members]) for k in range(members)]
    (tmp_path / "in.gz").write_bytes(b"".join(gzip.compress(p) for p in parts))
    files = pafs.LocalFileSystem()
    out = str(tmp_path / "out.warc.gz")
    assert W.normalise(files, str(tmp_path / "in.gz"), out) == 30
    raw = open(out, "rb").read()
    index = [json.loads(x) for x in open(out + ".idx")]
    order = [r for k in range(members) for r in recs[k::members]]
    assert [zlib.decompress(raw[e["offset"] : e["offset"] + e["length"]], 31) for e in index] == order
    assert gzip.decompress(raw) == b"".join(order)
    head, block = W.parse(order[0])
    assert head["warc-type"] == "response" and block.endswith(b"a\r\n\r\nb")


def test_cut_off_archive_is_an_error():
    with pytest.raises(ValueError):
        list(W.records([W.record("response", 1, "u", "d", 3, b"abc")[:-9]]))
    assert list(W.inflated(io.BytesIO(gzip.compress(b"x" * 10**6)))) != []
