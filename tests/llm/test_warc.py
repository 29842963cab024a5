import gzip
import hashlib
import zlib

import pytest
from pyspark.sql import types as T

from gridtide.llm import warc as W

SCHEMA = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("html", T.StringType()), T.StructField("digest", T.StringType())])
BIG = "<p>é</p>" * 40
ROWS = [(3, "http://a/1", BIG, "x"), (1, "http://a/2", BIG, "x"), (2, None, BIG, "x"), (4, "u\r\nX: y", "small", ""), (5, "u", "small", ""), (6, "u", None, ""), (7, "u", "\r\n\r\nWARC/1.1\r\n\r\n" * 30, ""), (8, "u", "z" * 900_000, "")]


def want(rows):
    groups = {}
    for i, _, h, _x in rows:
        groups.setdefault((h or "").encode(), []).append(i)
    out = set()
    for i, _, h, _x in rows:
        body = (h or "").encode()
        first = min(groups[body])
        again = len(body) >= 100 and i != first
        out.add((i, len(body), hashlib.sha256(body).hexdigest(), "revisit" if again else "response", first if again else None))
    return out


def test_round_trip(spark, monkeypatch):
    archives = W.Archives(spark)
    manifest = archives.write(spark.createDataFrame(ROWS, SCHEMA).repartition(2))
    index = archives.normalise(manifest)
    assert {tuple(r) for r in archives.read(index).collect()} == want(ROWS)
    assert sum(r.records for r in manifest.collect()) == index.count() == len(ROWS)
    mono, path = W.store_of(manifest.first().archive)
    raw = mono.open_input_stream(path, compression=None).read()
    d = zlib.decompressobj(31)
    d.decompress(raw)
    assert d.eof and not d.unused_data  # one stream for the whole file
    for r in index.collect():
        fs_, at = W.store_of(r.archive)
        member = fs_.open_input_file(at).read_at(r.length, r.offset)
        assert gzip.decompress(member).startswith(b"WARC/1.1\r\nWARC-Type: " + r.record_type.encode())
    fs_, at = W.store_of(index.first().archive + ".idx")
    assert len(fs_.open_input_stream(at).read().splitlines()) > 0


def test_records_are_cut_however_the_stream_is_fed():
    whole = b"".join(W.record(i, "u", b"p" * n, "response", None) for i, n in enumerate([0, 5, 3000]))
    for step in (1, 7, 100, 10**6):
        cut, got = W.Records(), []
        for a in range(0, len(whole), step):
            got += cut.feed(whole[a : a + step])
        assert b"".join(got) == whole and len(got) == 3


def test_edges(spark):
    archives = W.Archives(spark)
    read = lambda rows: archives.read(archives.normalise(archives.write(spark.createDataFrame(rows, SCHEMA))))
    assert read([]).count() == 0
    rows = sorted(((r.page_id or -1, r.record_type, r.refers_to) for r in read([(1, "u", BIG, ""), (1, "u", BIG, ""), (None, "u", BIG, ""), (9, "u", BIG, "")]).collect()), key=str)
    assert rows == [(-1, "revisit", 1), (1, "response", None), (1, "response", None), (9, "revisit", 1)]
