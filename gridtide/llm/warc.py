"""WARC archives: writing, the monolithic gzip normaliser, and reading by offset.

Archives arrive as one gzip stream a file, which can't be entered in the middle.
The normaliser inflates such a stream once, piece by piece, writes every record
as a gzip member of its own and leaves a sidecar index of offsets, so that any
record can be read alone afterwards.

Files lie below the session's shared folder and are opened through
``pyarrow.fs``, which takes local paths and store URLs alike.  A task writes
under a fresh name and only its manifest rows make a file count, so a repeated
task leaves at most an unused file.

Defined cases: null html is an empty payload; null page ids are kept and never
the target of a revisit while another id has the payload; rows that repeat the
smallest id of a payload are all responses; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import json
import uuid
import zlib

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import Scratch, partitions

LEAST = 100  # payload bytes from which equal payloads become revisits
ARCHIVE_BYTES = 64 << 20  # inflated bytes after which a task starts the next archive
PIECE = 1 << 18
DATE = "1970-01-01T00:00:00Z"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
MANIFEST = "archive string, records long"
INDEX = "archive string, offset long, length long, record_type string, page_id long"


def store_of(uri: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path or URL, and the path on it."""
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri.removeprefix("file:").lstrip("/")
    return fs.FileSystem.from_uri(uri)


def record(page_id, url, payload: bytes, kind: str, refers_to) -> bytes:
    """One WARC record; a revisit carries the HTTP head only."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http + (payload if kind == "response" else b"")
    digest = hashlib.sha256(payload).hexdigest()
    clean = "".join(c if c > " " else f"%{ord(c):02X}" for c in url) if url else "about:blank"
    head = [
        "WARC/1.1", f"WARC-Type: {kind}", f"WARC-Date: {DATE}", f"WARC-Target-URI: {clean}",
        f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page_id} {digest} {kind}')}>",
        f"WARC-Payload-Digest: sha256:{digest}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}",
    ]
    if page_id is not None:
        head.append(f"X-Page-Id: {page_id}")
    if kind == "revisit":
        head += [f"WARC-Profile: {PROFILE}", f"X-Refers-To-Page-Id: {refers_to}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_head(head: bytes) -> dict[str, str]:
    lines = head.decode().split("\r\n")
    return dict(line.split(": ", 1) for line in lines[1:] if line)


class Records:
    """Cuts a growing byte stream into whole records."""

    def __init__(self):
        self.held = bytearray()
        self.need = None

    def feed(self, data: bytes):
        self.held += data
        while True:
            if self.need is None:
                end = self.held.find(b"\r\n\r\n")
                if end < 0:
                    return
                self.need = end + 4 + int(parse_head(bytes(self.held[:end]))["Content-Length"]) + 4
            if len(self.held) < self.need:
                return
            yield bytes(self.held[: self.need])
            del self.held[: self.need]
            self.need = None


def _write(folder: str):
    def run(batches):
        store, path = store_of(folder)
        store.create_dir(path, recursive=True)
        done, sink, size, count, name = [], None, 0, 0, ""

        def close():
            sink.write(gz.flush())
            sink.close()
            done.append((f"{folder}/{name}", count))

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                if sink is None:
                    name, size, count = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                    sink, gz = store.open_output_stream(f"{path}/{name}", compression=None), zlib.compressobj(6, zlib.DEFLATED, 31)
                one = record(row[0], row[1], (row[2] or "").encode(), row[3], row[4])
                sink.write(gz.compress(one))
                size, count = size + len(one), count + 1
                if size >= ARCHIVE_BYTES:
                    close()
                    sink = None
        if sink is not None:
            close()
        yield pa.RecordBatch.from_arrays([pa.array([d[0] for d in done], pa.string()), pa.array([d[1] for d in done], pa.int64())], names=["archive", "records"])

    return run


def _normalise(folder: str):
    def run(batches):
        store, path = store_of(folder)
        store.create_dir(path, recursive=True)
        for batch in batches:
            for archive in batch.column(0).to_pylist():
                source, at = store_of(archive)
                name = f"{uuid.uuid4().hex}.warc.gz"
                rows, offset, cut = [], 0, Records()
                inflate = zlib.decompressobj(31)
                with source.open_input_stream(at, compression=None) as stream, store.open_output_stream(f"{path}/{name}", compression=None) as sink:

                    def member(one: bytes):
                        nonlocal offset
                        gz = zlib.compressobj(6, zlib.DEFLATED, 31)
                        body = gz.compress(one) + gz.flush()
                        sink.write(body)
                        head = parse_head(one[: one.index(b"\r\n\r\n")])
                        page = head.get("X-Page-Id")
                        rows.append((f"{folder}/{name}", offset, len(body), head["WARC-Type"], None if page is None else int(page)))
                        offset += len(body)

                    while data := stream.read(PIECE):
                        while data:
                            for one in cut.feed(inflate.decompress(data, PIECE)):
                                member(one)
                            data = inflate.unconsumed_tail
                            if inflate.eof:  # another member follows: some writers start one for each flush
                                data, inflate = inflate.unused_data, zlib.decompressobj(31)
                    for one in cut.feed(inflate.flush()):
                        member(one)
                with store.open_output_stream(f"{path}/{name}.idx", compression=None) as side:
                    side.write("".join(json.dumps({"offset": r[1], "length": r[2], "type": r[3], "page_id": r[4]}) + "\n" for r in rows).encode())
                for i in range(0, len(rows), 4096):
                    part = list(zip(*rows[i : i + 4096], strict=True))
                    kinds = (pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(part, kinds, strict=True)], names=["archive", "offset", "length", "record_type", "page_id"])

    return run


def _read(batches):
    held, handle = None, None
    for batch in batches:
        rows = []
        for archive, offset, length in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            if archive != held:
                if handle is not None:
                    handle.close()
                store, path = store_of(archive)
                held, handle = archive, store.open_input_file(path)
            whole = zlib.decompress(handle.read_at(length, offset), 31)
            end = whole.index(b"\r\n\r\n")
            head = parse_head(whole[:end])
            block = whole[end + 4 : end + 4 + int(head["Content-Length"])]
            body = block[block.index(b"\r\n\r\n") + 4 :]
            page, refers = head.get("X-Page-Id"), head.get("X-Refers-To-Page-Id")
            told = head["WARC-Payload-Digest"].removeprefix("sha256:")
            whole = head["WARC-Type"] == "response"
            rows.append((None if page is None else int(page), head["WARC-Type"], len(body) if whole else None, hashlib.sha256(body).hexdigest() if whole else None, told, None if refers is None else int(refers)))
        cols = list(zip(*rows, strict=True)) if rows else [()] * 6
        kinds = (pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["page_id", "record_type", "size", "digest", "told", "refers_to"])
    if handle is not None:
        handle.close()


class Archives:
    """A set of WARC archives below one folder."""

    def __init__(self, spark: SparkSession, scratch: Scratch | None = None):
        self.spark, self.scratch = spark, scratch or Scratch(spark, "warc")

    def write(self, pages: DataFrame) -> DataFrame:
        """Write one record a page into monolithic gzip archives; returns the manifest."""
        base = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
        base = base.withColumn("digest", F.unhex(F.sha2("html", 256)))
        same = base.where(F.octet_length("html") >= LEAST).groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
        same = self.scratch.keep(same, "same")  # only payloads that repeat
        typed = base.join(same, "digest", "left")
        again = F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
        typed = typed.select("page_id", "url", "html", F.when(again, "revisit").otherwise("response").alias("kind"), F.when(again, F.col("first")).alias("refers"))
        return self.scratch.keep(typed.mapInArrow(_write(f"{self.scratch.path}/mono"), MANIFEST), "manifest")

    def normalise(self, manifest: DataFrame) -> DataFrame:
        """One gzip member a record, with sidecar indexes; returns the index rows."""
        each = manifest.select("archive").repartition(max(partitions(self.spark), 1), "archive")
        return self.scratch.keep(each.mapInArrow(_normalise(f"{self.scratch.path}/members"), INDEX), "index")

    def read(self, index: DataFrame) -> DataFrame:
        """(page_id, payload_bytes, payload_digest, record_type, refers_to), revisits resolved through their response."""
        parts = index.repartition(partitions(self.spark), "archive", F.floor(F.col("offset") / (16 << 20))).sortWithinPartitions("archive", "offset")
        got = self.scratch.keep(parts.select("archive", "offset", "length").mapInArrow(_read, "page_id long, record_type string, size long, digest string, told string, refers_to long"), "read")
        full = got.where("record_type = 'response' and page_id is not null").select(F.col("page_id").alias("target"), F.col("digest").alias("t_digest"), F.col("size").alias("t_size")).dropDuplicates(["target", "t_digest"])
        found = got.join(full, (got.refers_to == full.target) & (got.told == full.t_digest), "left")
        return found.select("page_id", F.coalesce("size", "t_size").alias("payload_bytes"), F.coalesce("digest", "t_digest").alias("payload_digest"), "record_type", "refers_to")


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages written as monolithic archives, normalised, and read back through the index."""
    archives = Archives(spark)
    return archives.read(archives.normalise(archives.write(spark.read.parquet(f"{sf_dir}/pages.parquet"))))


SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, strlen(coalesce(html, '')) AS n FROM pages),
f AS (SELECT *, CASE WHEN n >= 100 THEN min(page_id) OVER (PARTITION BY body) ELSE page_id END AS first FROM p)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, sha256(body) AS payload_digest,
  CASE WHEN first = page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN first = page_id THEN NULL ELSE first END AS refers_to
FROM f
"""
