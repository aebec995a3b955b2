"""WARC archives: writing, normalising monolithic gzip files, and reading back.

``write_archives`` writes one record for each page into archives of bounded size.  An
archive is first one gzip stream over the whole file, as crawlers often leave it; the
normaliser inflates such a stream once, from end to end, writes every record as a gzip
member of its own, and leaves a sidecar index of their offsets, so that each record can be
read alone.  ``read_archives`` reads archives back through their sidecars.

Files are written by the executors through ``pyarrow.fs`` to a URI that all machines reach
(the shared folder).  Each attempt of a task writes under names of its own and renames
nothing; the manifest, which Spark writes from the attempts that count, publishes them.
``sweep`` deletes what lost or repeated attempts left.

Edge cases: null html is an empty payload; null page_id reads back as null; null url is
empty; payloads below ``MIN_REVISIT`` bytes are always responses; rows of one page_id and
one payload are all responses if that id is the largest; record ids name page and payload,
so pages of one id with several payloads have records of their own; other columns
aren't read.
"""

from __future__ import annotations

import hashlib
import json
import uuid
import zlib

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

MIN_REVISIT = 1000
ARCHIVE_BYTES = 16 << 20  # of payload in one archive, about
STEP = 1 << 18
LEVEL_WHOLE, LEVEL_MEMBER = 1, 4
DATE = "2024-01-01T00:00:00Z"
_GZIP = 31  # zlib's window setting for gzip headers


# ------------------------------------------------------------------ records
def record(kind: str, page, url: str, digest: str, size: int, body: bytes, refers_to=None) -> bytes:
    """One WARC/1.1 record; the extension fields carry the page id and payload size."""
    http = b""
    if kind != "warcinfo":
        http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % size
    block = http + body
    head = [
        ("WARC-Type", kind),
        ("WARC-Record-ID", record_id(page, digest)),
        ("WARC-Date", DATE),
        ("WARC-Target-URI", url),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("X-Payload-Length", str(size)),
        ("Content-Type", "application/http; msgtype=response" if http else "application/warc-fields"),
        ("Content-Length", str(len(block))),
    ]
    if refers_to is not None:
        head += [("WARC-Refers-To", record_id(refers_to, digest)), ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")]
    lines = "".join(f"{k}: {_plain(v)}\r\n" for k, v in head if v != "")
    return b"WARC/1.1\r\n" + lines.encode("utf-8", "surrogatepass") + b"\r\n" + block + b"\r\n\r\n"


def record_id(page, digest: str) -> str:
    return f"<urn:page:{'none' if page is None else page}:{digest or 'info'}>"


def _plain(value: str) -> str:
    return " ".join(value.split())


def parse(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields (lower-case names) and block of one record."""
    end = raw.index(b"\r\n\r\n") + 4
    head = dict(_field(x) for x in raw[:end].decode("utf-8", "surrogatepass").split("\r\n")[1:] if x)
    return head, raw[end : end + int(head["content-length"])]


def _field(line: str) -> tuple[str, str]:
    name, _, value = line.partition(":")
    return name.strip().lower(), value.strip()


def records(chunks):
    """Records as bytes from a stream of inflated bytes, in any cuts."""
    buf = bytearray()
    want = None
    for chunk in chunks:
        buf += chunk
        while True:
            if want is None:
                end = buf.find(b"\r\n\r\n")
                if end < 0:
                    break
                size = next(int(x[15:]) for x in bytes(buf[:end]).split(b"\r\n") if x[:15].lower() == b"content-length:")
                want = end + 4 + size + 4
            if len(buf) < want:
                break
            yield bytes(buf[:want])
            del buf[:want]
            want = None
    if buf.strip(b"\r\n"):
        raise ValueError("the last record is cut off")


def inflated(stream):
    """The inflated bytes of a gzip file, of one member or many, in bounded steps."""
    z = zlib.decompressobj(_GZIP)
    while raw := stream.read(STEP):
        while raw:
            if z.eof:
                z = zlib.decompressobj(_GZIP)
            out = z.decompress(raw, STEP)
            if out:
                yield out
            raw = z.unconsumed_tail or z.unused_data
    if not z.eof and (rest := z.flush()):
        yield rest


# ------------------------------------------------------------------ the normaliser
def normalise(files: pafs.FileSystem, source: str, target: str) -> int:
    """Rewrite a gzip WARC file with one member for each record, and its sidecar
    ``target + '.idx'`` of JSON lines (offset, length, type, id).  Returns the records."""
    done, at = 0, 0
    with files.open_input_stream(source, compression=None) as stream, files.open_output_stream(target, compression=None) as out, files.open_output_stream(target + ".idx", compression=None) as side:
        for raw in records(inflated(stream)):
            z = zlib.compressobj(LEVEL_MEMBER, zlib.DEFLATED, _GZIP)
            member = z.compress(raw) + z.flush()
            out.write(member)
            head = dict(_field(x) for x in raw[: raw.index(b"\r\n\r\n")].decode("utf-8", "surrogatepass").split("\r\n")[1:])
            line = {"offset": at, "length": len(member), "type": head["warc-type"], "id": head["warc-record-id"]}
            side.write((json.dumps(line) + "\n").encode())
            at += len(member)
            done += 1
    return done


def _write(uri: str, keep_whole: bool):
    def run(batches):
        files, root = pafs.FileSystem.from_uri(uri)
        task = TaskContext.get()
        name, seq = f"{root}/part-{task.partitionId():06d}-{task.taskAttemptId()}-{uuid.uuid4().hex[:8]}", 0
        out = path = z = None
        size = 0

        def finish():
            out.write(z.flush())
            out.close()
            n = normalise(files, path + ".whole", path)
            if not keep_whole:
                files.delete_file(path + ".whole")
            return pa.record_batch([pa.array([path]), pa.array([n - 1], pa.int64())], names=["path", "n_records"])

        for batch in batches:
            for page, url, html, digest, refers in zip(*(batch.column(c) for c in ("page_id", "url", "html", "digest", "refers_to"))):
                body = C.encoded(html.as_py())
                if out is None:
                    path = f"{name}-{seq:04d}.warc.gz"
                    out, z = files.open_output_stream(path + ".whole", compression=None), zlib.compressobj(LEVEL_WHOLE, zlib.DEFLATED, _GZIP)
                    out.write(z.compress(record("warcinfo", None, "", "", 0, b"software: curvetide\r\n")))
                refers = refers.as_py()
                kind = "response" if refers is None else "revisit"
                out.write(z.compress(record(kind, page.as_py(), url.as_py() or "", digest.as_py(), len(body), body if refers is None else b"", refers)))
                size += len(body)
                if size >= ARCHIVE_BYTES:
                    yield finish()
                    out, size, seq = None, 0, seq + 1
        if out is not None:
            yield finish()

    return run


def _page(urn: str | None):
    value = urn and urn[len("<urn:page:") : -1].split(":")[0]
    return None if value in (None, "none") else int(value)


def _read(uri: str):
    def run(batches):
        files, _ = pafs.FileSystem.from_uri(uri)
        for batch in batches:
            for path in batch.column("path").to_pylist():
                rows = [[] for _ in range(6)]
                with files.open_input_stream(path + ".idx", compression=None) as side:
                    index = [json.loads(x) for x in side.read().decode().splitlines()]
                with files.open_input_file(path) as archive:
                    for entry in index:
                        if entry["type"] == "warcinfo":
                            continue
                        archive.seek(entry["offset"])
                        head, block = parse(zlib.decompress(archive.read(entry["length"]), _GZIP))
                        body = block[block.index(b"\r\n\r\n") + 4 :]
                        digest, size = head["warc-payload-digest"].removeprefix("sha1:"), int(head["x-payload-length"])
                        if head["warc-type"] == "response":
                            if len(body) != size or hashlib.sha1(body).hexdigest() != digest:
                                raise ValueError(f"{path}: payload of {entry['id']} is damaged")
                        for r, v in zip(rows, (_page(entry["id"]), head.get("warc-target-uri"), size, digest, head["warc-type"], _page(head.get("warc-refers-to")))):
                            r.append(v)
                types = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64())
                yield pa.record_batch([pa.array(r, t) for r, t in zip(rows, types)], names=["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    return run


# ------------------------------------------------------------------ the operators
def plan_records(pages: DataFrame, least: int = MIN_REVISIT) -> DataFrame:
    """(page_id, url, html, digest, refers_to): a payload of at least ``least`` bytes that
    a page of larger id has too refers to the largest."""
    C.need(pages, "page_id", "url", "html")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce("html", F.lit("")).alias("html"))
    rows = rows.withColumn("digest", F.sha1(F.col("html").cast("binary")))
    size = F.octet_length("html")
    twice = rows.where(size >= least).groupBy("digest").agg(F.max("page_id").alias("last"), F.min("page_id").alias("first")).where("first <> last").select("digest", "last")
    twice = C.materialize(twice, "warc-twice")
    refers = F.when((size >= least) & (F.col("page_id") < F.col("last")), F.col("last"))
    return rows.join(twice, "digest", "left").select("page_id", "url", "html", "digest", refers.alias("refers_to"))


def write_archives(pages: DataFrame, uri: str, keep_whole: bool = False) -> DataFrame:
    """Write archives under ``uri``; returns the manifest (path, n_records)."""
    files, root = pafs.FileSystem.from_uri(uri)
    files.create_dir(root, recursive=True)
    return C.materialize(plan_records(pages).mapInArrow(_write(uri, keep_whole), "path string, n_records long"), "warc-manifest")


def sweep(manifest: DataFrame, uri: str) -> int:
    """Delete files under ``uri`` that no archive of the manifest owns; returns how many.
    For a time when no task writes there any more."""
    files, root = pafs.FileSystem.from_uri(uri)
    spark = manifest.sparkSession
    there = [f.path for f in files.get_file_info(pafs.FileSelector(root)) if f.is_file]
    owner = F.regexp_replace("file", r"\.(idx|whole)$", "")
    found = spark.createDataFrame([(f,) for f in there], "file string").withColumn("path", owner)
    lost = [r["file"] for r in found.join(manifest, "path", "left_anti").collect()]
    for path in lost:
        files.delete_file(path)
    return len(lost)


def read_archives(manifest: DataFrame, uri: str) -> DataFrame:
    """Records (page_id, url, payload_bytes, payload_digest, record_type, refers_to)."""
    spread = manifest.select("path").repartition(C.shuffle_width(manifest.sparkSession))
    return spread.mapInArrow(_read(uri), "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long")


def op3_warc(spark, sf_dir: str) -> DataFrame:
    with C.Scratch(spark) as tables:
        path = C.fresh_path(spark, "warc")
        C.note(path)
        manifest = write_archives(C.read_table(spark, sf_dir, "pages", "page_id", "url", "html"), _uri(path))
        return tables.keep(read_archives(manifest, _uri(path)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"), "warc-result")


def _uri(path: str) -> str:
    if "://" in path:
        return path
    return "file://" + path.removeprefix("file:")
