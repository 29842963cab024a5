"""Exact deduplication with a log-structured merge index of text digests.

Every row's normalised text gets its SHA-256.  Tasks fill memtables with the
digests and flush them as runs: for each digest bucket a segment, sorted by digest,
with a Bloom filter of its own.  Compaction merges the segments of a bucket, the
two smallest first: the one's filter tells which digests of the other it may hold,
only those are searched for, and two segments without such a digest are merged
unsearched.  Of a digest's entries the one that stays is kept: most code points,
then smallest id.  A digest that is held more than once is a hit, and the bytes of
all its rows are compared with those of the entry that stays.

The index also takes batch after batch (:meth:`DigestIndex.flush`) and is asked
with a batch (:meth:`DigestIndex.lookup`): filters are read first, and only
segments that a filter can't rule out are read at all.

Defined cases: null text counts as empty; all blank texts are equal; of equally
long texts one with an id stays before one without; of rows that repeat an id and a
text, and of rows without an id, one stays (the first by file and place); a text of
any length is hashed and compared whole; further columns, whatever their names, are
not read; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import heapq
from dataclasses import dataclass
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .store import Scratch, bounded, free_name, partitions, with_row_ids

BLANK = bytes(K.BLANKS)
MEMTABLE = 1 << 16  # rows of a memtable before a flush
BUCKET_ROWS = 1 << 18  # rows that a bucket holds on average at most
WIDTH = 32  # bytes of a digest
BITS, PROBES = 12, 4  # filter bits an entry, bits set for each
CHUNK = 512  # members compared in one salted group

ROW = "doc_id long, place long, sha binary, chars long"
ENTRY = "digest binary, doc_id long, place long, chars long, copies long"
SEGMENT = "run long, bucket int, digests binary, ids binary, absent binary, places binary, chars binary, copies binary, bits long, filter binary"
NUMBERS = ("ids", "places", "chars", "copies")


def _bodies(texts: K.Texts):
    raw = texts.data.tobytes()
    for a, b in zip(texts.offs[:-1], texts.offs[1:], strict=True):
        yield raw[a:b].translate(None, BLANK)


def _code_points(texts: K.Texts) -> np.ndarray:
    heads = np.concatenate([[0], np.cumsum((texts.data & 0xC0) != 0x80)])
    return np.diff(heads[texts.offs])


def _digested(batches):
    for batch in K.chunks(batches, "text"):
        texts = K.Texts(batch.column(2))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array([hashlib.sha256(x).digest() for x in _bodies(texts)], pa.binary()), pa.array(_code_points(texts))],
            names=[f.split()[0] for f in ROW.split(", ")],
        )


def _with_bodies(batches):
    for batch in K.chunks(batches, "text"):
        bodies = list(_bodies(K.Texts(batch.column(1))))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([hashlib.sha256(x).digest() for x in bodies], pa.binary()), pa.array(bodies, pa.binary())], names=["place", "sha", "body"])


@dataclass
class Segment:
    """Entries of one bucket, sorted by digest (four big-endian words a row), each digest once."""

    words: np.ndarray
    ids: np.ndarray
    absent: np.ndarray
    places: np.ndarray
    chars: np.ndarray
    copies: np.ndarray
    bits: int = 0
    held: np.ndarray | None = None

    def __len__(self) -> int:
        return len(self.words)

    def take(self, rows: np.ndarray) -> Segment:
        return Segment(self.words[rows], self.ids[rows], self.absent[rows], self.places[rows], self.chars[rows], self.copies[rows])

    @staticmethod
    def collapsed(words: np.ndarray, ids, absent, places, chars, copies) -> Segment:
        """Of each digest the entry that stays, with the copies of all."""
        order = np.lexsort((places, ids, absent, -chars, *words.T[::-1]))
        words, copies = words[order], copies[order]
        heads = np.flatnonzero(np.append(True, (words[1:] != words[:-1]).any(axis=1))[: len(words)])
        first = order[heads]
        return Segment(words[heads], ids[first], absent[first], places[first], chars[first], np.add.reduceat(copies, heads) if len(heads) else copies)

    def filtered(self) -> Segment:
        """With its Bloom filter."""
        if self.held is None:
            self.bits = max(64, len(self) * BITS)
            self.held = np.zeros(self.bits, bool)
            self.held[_probes(self.words, self.bits).ravel()] = True
        return self

    def maybe(self, words: np.ndarray) -> np.ndarray:
        """Rows of ``words`` that the filter doesn't rule out."""
        return np.flatnonzero(self.held[_probes(words, self.bits)].all(axis=1))

    def find(self, words: np.ndarray) -> np.ndarray:
        """Place of each digest in this segment, -1 where it isn't held."""
        at, stop = (np.searchsorted(self.words[:, 0], words[:, 0], side=x) for x in ("left", "right"))
        out = np.full(len(words), -1)
        while (open_ := np.flatnonzero((out < 0) & (at < stop))).size:  # more than once only where first words agree
            same = (self.words[at[open_]] == words[open_]).all(axis=1)
            out[open_[same]] = at[open_[same]]
            at[open_] += 1
        return out

    def merge(self, other: Segment) -> Segment:
        """Both as one; only digests that pass this segment's filter are searched for."""
        maybe = self.filtered().maybe(other.words)
        hit = np.zeros(0, np.int64)
        if len(maybe):
            at = self.find(other.words[maybe])
            hit, at = maybe[at >= 0], at[at >= 0]
        if len(hit):
            mine, theirs = self.take(at), other.take(hit)
            better = np.lexsort((np.tile([0, 1], len(at)), *(_pairs(getattr(mine, c), getattr(theirs, c)) for c in ("places", "ids", "absent")), -_pairs(mine.chars, theirs.chars), np.repeat(np.arange(len(at)), 2)))
            theirs_stay = better[::2] % 2 == 1
            for c in ("ids", "absent", "places", "chars"):
                getattr(self, c)[at[theirs_stay]] = getattr(theirs, c)[theirs_stay]
            self.copies[at] += theirs.copies
        rest = other.take(np.setdiff1d(np.arange(len(other)), hit, True))
        both = [np.concatenate([getattr(self, c), getattr(rest, c)]) for c in ("words", "ids", "absent", "places", "chars", "copies")]
        return Segment(*both).take(np.lexsort(both[0].T[::-1]))


def _pairs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.stack([a, b], axis=1).ravel()


def _probes(words: np.ndarray, bits: int) -> np.ndarray:
    """Filter positions of each digest, PROBES a row."""
    steps = np.arange(PROBES, dtype=np.uint64)[None, :]
    return ((words[:, 1:2] + steps * (words[:, 2:3] | np.uint64(1))) % np.uint64(bits)).astype(np.int64)


def _words_of(blob: bytes) -> np.ndarray:
    return np.frombuffer(blob, ">u8").astype(np.uint64).reshape(-1, WIDTH // 8)


def _bucket_of(words: np.ndarray, buckets: int) -> np.ndarray:
    return (((words[:, 0] >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)).astype(np.int64)


def _written(segments: list[tuple[int, int, Segment]]) -> pa.RecordBatch:
    """Segments as rows of SEGMENT."""
    cols = [[] for _ in range(10)]
    for run, bucket, s in segments:
        s.filtered()
        blobs = [s.words.astype(">u8").tobytes(), s.ids.tobytes(), s.absent.tobytes(), *(getattr(s, c).tobytes() for c in NUMBERS[1:])]
        for col, value in zip(cols, [run, bucket, *blobs, s.bits, np.packbits(s.held).tobytes()], strict=True):
            col.append(value)
    kinds = [pa.int64(), pa.int32(), *[pa.binary()] * 6, pa.int64(), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[f.split()[0] for f in SEGMENT.split(", ")])


def _read(digests, ids, absent, *numbers) -> Segment:
    return Segment(_words_of(digests), np.frombuffer(ids, np.int64).copy(), np.frombuffer(absent, np.uint8).copy(), *(np.frombuffer(x, np.int64).copy() for x in numbers))


def _flushed(buckets: int, key_bytes: int):
    """A task's rows as runs: each memtable becomes a segment for every bucket it has entries of."""

    def run(batches):
        from pyspark import TaskContext

        context = TaskContext.get()
        number = count((context.partitionId() if context else 0) << 24)
        table: list[pa.RecordBatch] = []

        def flush():
            rows = pa.Table.from_batches(table)
            table.clear()
            digests = b"".join(x[:key_bytes].ljust(WIDTH, b"\0") for x in rows.column("sha").to_pylist())
            ids = rows.column("doc_id")
            one = Segment.collapsed(
                _words_of(digests), np.asarray(ids.fill_null(0), np.int64), np.asarray(ids.is_null(), np.uint8), np.asarray(rows.column("place"), np.int64), np.asarray(rows.column("chars"), np.int64), np.ones(len(rows), np.int64)
            )
            bucket = _bucket_of(one.words, buckets)  # rises with the digest
            cuts = np.append(np.flatnonzero(np.diff(bucket, prepend=-1)), len(bucket))
            mine = next(number)
            return _written([(mine, int(bucket[a]), one.take(np.arange(a, b))) for a, b in zip(cuts[:-1], cuts[1:], strict=True)])

        held = 0
        for batch in batches:
            if batch.num_rows:
                table.append(batch)
                held += batch.num_rows
            if held >= MEMTABLE:
                yield flush()
                held = 0
        if held:
            yield flush()

    return run


def _compacted(batches):
    """One segment a bucket from those of all runs; rows come sorted by bucket."""

    def merged(bucket: int, held: list[Segment]):
        order = count()
        heap = [(len(s), next(order), s) for s in held]
        heapq.heapify(heap)
        while len(heap) > 1:
            small, large = heapq.heappop(heap)[2], heapq.heappop(heap)[2]
            one = large.merge(small)
            heapq.heappush(heap, (len(one), next(order), one))
        return _written([(0, bucket, heap[0][2])])

    bucket, held = None, []
    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if row[0] != bucket:
                if held:
                    yield merged(bucket, held)
                bucket, held = row[0], []
            held.append(_read(*row[1:]))
    if held:
        yield merged(bucket, held)


def _entries(batches):
    """Segments as rows of ENTRY."""
    for batch in batches:
        for row in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
            s = _read(*row)
            raw = s.words.astype(">u8").tobytes()
            yield pa.RecordBatch.from_arrays(
                [pa.array([raw[i : i + WIDTH] for i in range(0, len(raw), WIDTH)], pa.binary()), pa.array(s.ids, mask=s.absent.astype(bool)), pa.array(s.places), pa.array(s.chars), pa.array(s.copies)],
                names=[f.split()[0] for f in ENTRY.split(", ")],
            )


def _probed(key, asked: pa.Table, filters: pa.Table) -> pa.Table:
    """(run, bucket, digests): what each run's filter lets pass of the digests asked for in one bucket."""
    blobs = asked.column("digests").to_pylist()
    words = np.unique(np.concatenate([_words_of(b) for b in blobs]), axis=0) if blobs else np.zeros((0, WIDTH // 8), np.uint64)
    found = []
    for run, bits, blob in zip(*(filters.column(c).to_pylist() for c in ("run", "bits", "filter")), strict=True):
        s = Segment(words, *[words[:, 0]] * 5, bits, np.unpackbits(np.frombuffer(blob, np.uint8))[:bits].astype(bool))
        passed = s.maybe(words)
        if len(passed):
            found.append((run, key[0].as_py(), words[passed].astype(">u8").tobytes()))
    cols = list(zip(*found, strict=True)) if found else [()] * 3
    return pa.table({"run": pa.array(cols[0], pa.int64()), "bucket": pa.array(cols[1], pa.int32()), "asked": pa.array(cols[2], pa.binary())})


def _searched(batches):
    """Entries of segments that are among the digests asked of them."""
    for batch in batches:
        for asked, *row in zip(*(batch.column(i).to_pylist() for i in range(7)), strict=True):
            s = _read(*row)
            at = s.find(_words_of(asked))
            hit = s.take(at[at >= 0])
            if len(hit):
                yield from _entries([_written([(0, 0, hit)]).select(COLUMNS)])


COLUMNS = ["digests", "ids", "absent", "places", "chars", "copies"]


def digested(documents: DataFrame, place: str) -> DataFrame:
    """(doc_id, place, sha, chars) of every row."""
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(place).alias("place"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(_digested, ROW)


class DigestIndex:
    """A persistent index of digests: batches are flushed as runs, and runs are compacted.

    The first batch sets the number of buckets, so that a bucket, which one
    task merges, holds BUCKET_ROWS rows on average at most; ``buckets`` plans for
    more.
    """

    def __init__(self, spark: SparkSession, scratch: Scratch | None = None, key_bytes: int = WIDTH, buckets: int | None = None):
        self.spark, self.scratch, self.key_bytes, self.buckets = spark, scratch or Scratch(spark, "digests"), key_bytes, buckets
        self.tables: list[str] = []
        self.made = 0

    def _segments(self, rows: DataFrame) -> DataFrame:
        if self.buckets is None:
            self.buckets = max(4 * partitions(self.spark), -(-rows.count() // BUCKET_ROWS))
        return rows.mapInArrow(_flushed(self.buckets, self.key_bytes), SEGMENT)

    def _add(self, segments: DataFrame) -> DataFrame:
        name = f"segments-{self.made}"
        self.made += 1
        self.tables.append(name)
        return self.scratch.keep(segments, name)

    def _all(self, *columns: str) -> DataFrame:
        """Segments of all tables; a table's number is part of the run's name."""
        out = None
        for k, name in enumerate(self.tables):
            part = self.scratch.read(name, SEGMENT).select(F.lit(k).alias("table"), *columns)
            out = part if out is None else out.unionByName(part)
        return out if out is not None else self.spark.createDataFrame([], SEGMENT).select(F.lit(0).alias("table"), *columns)

    def flush_rows(self, rows: DataFrame) -> None:
        """Add rows (doc_id, place, sha, chars)."""
        self._add(self._segments(rows))

    def flush(self, documents: DataFrame) -> None:
        """Add a batch of documents."""
        place = free_name(documents.columns, "place")
        self.flush_rows(digested(with_row_ids(documents, place, self.scratch), place))

    def probe(self, documents: DataFrame) -> DataFrame:
        """(run, bucket, asked, table): segments that may hold digests of a batch, and which; no others need be read."""
        asked = self._segments(digested(documents.withColumn(free_name(documents.columns, "place"), F.lit(0).cast("long")), free_name(documents.columns, "place")))
        out = None
        for k, name in enumerate(self.tables):
            filters = self.scratch.read(name, SEGMENT).select("run", "bucket", "bits", "filter")
            found = asked.select("bucket", "digests").groupBy("bucket").cogroup(filters.groupBy("bucket")).applyInArrow(_probed, "run long, bucket int, asked binary")
            found = found.withColumn("table", F.lit(k))
            out = found if out is None else out.unionByName(found)
        return out

    def lookup(self, documents: DataFrame) -> DataFrame:
        """(digest, doc_id, place, chars, copies) of the entries that a batch of texts hits, by table and run."""
        if not self.tables:
            return self.spark.createDataFrame([], ENTRY)
        may = self.scratch.keep(self.probe(documents), f"asked-{self.made}")
        segments = self._all("run", "bucket", *COLUMNS)
        return segments.join(may, ["table", "run", "bucket"]).select("asked", *COLUMNS).mapInArrow(_searched, ENTRY)

    def compact(self) -> None:
        """Merge all runs into one; each digest keeps the entry that stays."""
        old = list(self.tables)
        dealt = self._all("bucket", *COLUMNS).drop("table").repartition(partitions(self.spark), "bucket").sortWithinPartitions("bucket")
        self._add(dealt.mapInArrow(_compacted, SEGMENT))
        self.tables = self.tables[-1:]
        self.scratch.drop(*old)

    def entries(self) -> DataFrame:
        """(digest, doc_id, place, chars, copies) of all runs; after :meth:`compact` each digest once."""
        return self._all(*COLUMNS).drop("table").mapInArrow(_entries, ENTRY)


def exact_duplicates(documents: DataFrame, scratch: Scratch | None = None, key_bytes: int = WIDTH, row: str | None = None) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) for every row, and ``row`` if that unique long column is named.

    ``key_bytes`` shortens the index key; whatever then falls together wrongly
    is parted again by the byte verification.
    """
    scratch = scratch or Scratch(documents.sparkSession, "exact")
    place = row or free_name(documents.columns, "place")
    docs = documents if row else with_row_ids(documents.select("doc_id", "text"), place, scratch)
    key = F.rpad(F.substring("sha", 1, key_bytes), F.lit(WIDTH), F.lit(bytearray(1))).alias("digest") if key_bytes < WIDTH else F.col("sha").alias("digest")
    rows = scratch.keep(digested(docs, place), "rows")
    index = DigestIndex(documents.sparkSession, scratch, key_bytes)
    index.flush_rows(rows)
    index.compact()
    hits = index.entries().where("copies > 1").select("digest", F.col("doc_id").alias("keep_id"), F.col("place").alias("keep_place"), F.col("copies").alias("size"))
    hits = scratch.keep(hits, "hits")
    rows = rows.select("doc_id", "place", "chars", "sha", key)
    # byte verification of every hit; a large group is compared in salted chunks
    members = scratch.keep(rows.join(hits, "digest", "left_semi").select("place"), "members")
    some = docs.select(F.col(place).alias("place"), F.col("text").cast("string").alias("text")).join(bounded(members), "place", "left_semi")
    held = some.mapInArrow(_with_bodies, "place long, sha binary, body binary").select("place", key, "body")
    held = scratch.keep(held.join(hits.withColumn("chunks", F.ceil(F.col("size") / CHUNK).cast("int")), "digest"), "bodies")
    stays = held.where("place = keep_place").select("digest", F.col("body").alias("keep_body"), F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"))
    told = held.withColumn("chunk", F.pmod(F.xxhash64("place"), F.col("chunks")).cast("int"))
    bad = told.join(stays, ["digest", "chunk"]).where("body <> keep_body").select("digest", "place", "body")
    bad = scratch.keep(bad, "unequal")
    scratch.drop("bodies")
    best = rows.join(hits, "digest", "left")
    if not bad.isEmpty():  # different bytes under one key: those rows are grouped by their bytes
        order = F.struct((-F.col("chars")).alias("less"), F.col("doc_id").isNull().alias("none"), "doc_id", "place")
        bad = bad.join(rows.select("place", "doc_id", "chars"), "place")
        groups = bad.groupBy("digest", "body").agg(F.min(order).alias("b"), F.count("*").alias("own_size"))
        own = bad.join(groups, ["digest", "body"]).select("place", F.col("b.doc_id").alias("own_id"), F.col("b.place").alias("own_place"), "own_size")
        gone = bad.groupBy("digest").agg(F.count("*").alias("gone"))
        best = best.join(own, "place", "left").join(gone, "digest", "left")
        best = best.withColumn("size", F.coalesce("own_size", F.col("size") - F.coalesce("gone", F.lit(0))))
        mine = F.col("own_place").isNotNull()
        best = best.withColumn("keep_id", F.when(mine, F.col("own_id")).otherwise(F.col("keep_id"))).withColumn("keep_place", F.coalesce("own_place", "keep_place"))
    single = F.col("size").isNull()
    return best.select(
        "doc_id",
        F.when(single, F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"),
        F.coalesce("size", F.lit(1)).cast("long").alias("group_size"),
        (single | (F.col("place") == F.col("keep_place"))).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
        *([F.col("place").alias(row)] if row else []),
    )


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact duplicate groups of all documents."""
    return exact_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


SQL = """
WITH t AS (
  SELECT doc_id, length(coalesce(text, '')) AS chars,
         regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]', '', 'g') AS body
  FROM documents)
SELECT doc_id,
       first_value(doc_id) OVER w AS keep_id,
       count(*) OVER (PARTITION BY body) AS group_size,
       doc_id = first_value(doc_id) OVER w AS kept,
       sha256(body) AS text_sha256
FROM t WINDOW w AS (PARTITION BY body ORDER BY chars DESC, doc_id)
"""
