"""Line deduplication by a suffix array over line ids.

A document is its sequence of lines (blank ones left out), each an id: 128 bits of
a cryptographic digest of its words in order, so equal ids are equal lines.
Suffixes are ranked by distributed prefix doubling: at depth ``d`` suffixes with
equal first ``d`` lines share a rank, ranks follow the order of those lines, and
depth doubles by ranking pairs of ranks.  Only suffixes whose first ``d`` lines
occur elsewhere stay active, so the work shrinks with the repeated text.

What counts as a repeated run is its size: ``min_words`` words, in however many
lines.  Each suffix is asked at the depths at which a run first has that size,
counted from its first line or back from its last.  Suffixes whose longest common
prefix reaches such a depth ``n`` lie in one interval; it is found by the ranks at
the largest power of two up to ``n``, of the suffix and of the suffix that ends with
the run.  All of an interval but its earliest suffix are later copies.  Copies that
follow one another on one diagonal (the same two documents and distance) are joined
to maximal runs, and the runs' lines are deleted.  As every line of a repeated run
of that size lies in one of those prefixes, no such run is missed, whatever its
length; and depths beyond ``min_words`` need no ranks.

Defined cases: documents are ordered by id, then by a digest of the text, and lines
by place; null and blank texts have no line and stay as they are; rows without an
id are left alone; rows that repeat an id and a text share their fate; a copy that
overlaps its original loses only what lies behind the original; texts and lines of
any length are worked on whole; further columns, whatever their names, are not
read; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import kernel as K
from .store import BROADCAST_ROWS, Scratch, partitions

MIN_WORDS = 50  # words of a run that is deleted
LONG_LINE = 1 << 16
KEY = ["doc_id", "th"]
LINES = "doc_id long, th long, ln int, r long, s long, words int, sizes array<int>"
BLANK_RUN = re.compile(rb"[\x20\x09-\x0d]+")


def _line(piece: bytes) -> tuple[bytes, int]:
    """(words joined by single blanks, number of words) of a line."""
    if len(piece) < LONG_LINE:
        words = piece.split()
        return b" ".join(words), len(words)
    body = BLANK_RUN.sub(b" ", piece).strip(b" ")
    return body, body.count(b" ") + 1 if body else 0


def _pieces(raw: bytes) -> list[bytes]:
    """Lines with their newline."""
    parts = raw.split(b"\n")
    return [x + b"\n" for x in parts[:-1]] + ([parts[-1]] if parts[-1] else [])


def run_sizes(words: list[int], least: int) -> list[list[int]]:
    """For each line the lengths of runs from it that have ``least`` words and would have fewer without their first or last line."""
    out: list[list[int]] = [[] for _ in words]
    start, total = 0, 0
    for stop, n in enumerate(words):  # the shortest run that ends here
        total += n
        while total - words[start] >= least:
            total -= words[start]
            start += 1
        if total >= least:
            out[start].append(stop - start + 1)
    stop, total = 0, 0
    for start, n in enumerate(words):  # the shortest run that starts here
        while stop < len(words) and total < least:
            total += words[stop]
            stop += 1
        if total >= least and (not out[start] or stop - start not in out[start]):
            out[start].append(stop - start)
        total -= n
    return out


def _lines(least: int):
    def run(batches):
        for batch in K.chunks(batches, "text"):
            owner, place, ids, count, sizes = [], [], [], [], []
            for i, text in enumerate(batch.column(2)):
                held = []
                for piece in (text.as_buffer().to_pybytes() if text.is_valid else b"").split(b"\n"):
                    body, n = _line(piece)
                    if n:
                        ids.append(hashlib.blake2b(body, digest_size=16).digest())
                        held.append(n)
                owner += [i] * len(held)
                place += range(len(held))
                count += held
                sizes += run_sizes(held, least)
            pair = np.frombuffer(b"".join(ids), np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(owner, pa.int64())), batch.column(1).take(pa.array(owner, pa.int64())), pa.array(place, pa.int32()), pa.array(pair[:, 0]), pa.array(pair[:, 1]), pa.array(count, pa.int32()), pa.array(sizes, pa.list_(pa.int32()))],
                names=["doc_id", "th", "ln", "r", "s", "words", "sizes"],
            )

    return run


def _cleaned(batches):
    for batch in K.chunks(batches, "text"):
        out, lines, gone = [], [], []
        for text, drops in zip(batch.column(1), batch.column(2).to_pylist(), strict=True):
            raw, drops, n, kept = text.as_buffer().to_pybytes() if text.is_valid else b"", set(drops or ()), 0, []
            for piece in _pieces(raw):
                full = not piece.isspace()
                if not (full and n in drops):
                    kept.append(piece)
                n += full
            out.append(b"".join(kept).decode())
            lines.append(n)
            gone.append(len(drops))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(lines, pa.int64()), pa.array(gone, pa.int64()), pa.array(out, pa.large_string()).cast(pa.string())],
            names=["doc_id", "n_lines", "n_deleted", "clean_text"],
        )


class LineRuns:
    """Repeated line runs of a corpus, and the texts without their later copies."""

    def __init__(self, spark: SparkSession, min_words: int = MIN_WORDS, scratch: Scratch | None = None):
        self.spark, self.min_words = spark, min_words
        self.scratch = scratch or Scratch(spark, "lines")

    def _ranked(self, pairs: DataFrame, tag: str) -> DataFrame:
        """``rank`` (r, s -> start of its interval in the suffix order) of each pair that occurs more than once.

        Only the distinct pairs are sorted: ranges of them in parallel, with the
        ranges' sizes (one number each) added up on the driver.
        """
        counted = pairs.groupBy("r", "s").agg(F.count("*").alias("n")).where("n > 1")
        spread = counted.repartitionByRange(partitions(self.spark), "r", "s").withColumn("part", F.spark_partition_id())
        spread = self.scratch.keep(spread, f"{tag}-pairs")
        sizes = {row.part: row.n for row in spread.groupBy("part").agg(F.sum("n").alias("n")).collect()}
        base, at = [], 0
        for part in sorted(sizes):
            base.append((part, at))
            at += sizes[part]
        base = self.spark.createDataFrame(base, "part int, base long")
        run = Window.partitionBy("part").orderBy("r", "s").rowsBetween(Window.unboundedPreceding, -1)
        placed = spread.withColumn("before", F.coalesce(F.sum("n").over(run), F.lit(0)))
        return placed.join(F.broadcast(base), "part").select("r", "s", (F.col("base") + F.col("before")).alias("rank"))

    def _asked(self, active: DataFrame, depth: int) -> DataFrame:
        """(doc_id, th, ln, size, rank, tail): runs of ``depth`` to under twice as many lines, named by the ranks of both ends."""
        each = active.select(*KEY, "ln", "rank", F.explode("sizes").alias("size"))
        even = each.where(F.col("size") == depth).withColumn("tail", F.col("rank"))
        if depth == 1:
            return even
        ends = active.select(*KEY, F.col("ln").alias("end"), F.col("rank").alias("tail"))
        longer = each.where((F.col("size") > depth) & (F.col("size") < 2 * depth)).withColumn("end", F.col("ln") + F.col("size") - depth)
        return even.unionByName(longer.join(ends, [*KEY, "end"]).drop("end"))

    def repeats(self, documents: DataFrame) -> DataFrame:
        """(doc_id, th, ln, size, first): suffixes whose first ``size`` lines are a later copy, with the earliest suffix of their interval."""
        keep, drop = self.scratch.keep, self.scratch.drop
        docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("doc_id is not null")
        now = keep(docs.select("doc_id", F.xxhash64("text").alias("th"), "text").mapInArrow(_lines(self.min_words), LINES), "all")
        depth, found = 1, self.spark.createDataFrame([], "doc_id long, th long, ln int, size int, first struct<doc_id:long,th:long,ln:int>")
        while True:
            rank = keep(self._ranked(now, f"d{depth}"), f"d{depth}-ranks")
            active = now.join(rank, ["r", "s"]).select(*KEY, "ln", "rank", "sizes")
            active = keep(active.dropDuplicates([*KEY, "ln"]) if depth == 1 else active, f"d{depth}")
            drop(f"d{depth}-pairs", f"d{depth}-ranks", f"d{depth // 2}")
            asked = keep(self._asked(active, depth), f"d{depth}-asked")
            interval = ["rank", "tail", "size"]
            first = asked.groupBy(*interval).agg(F.min(F.struct(*KEY, "ln")).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
            first = keep(first, f"d{depth}-first")  # written, so that a large interval's join can be split
            later = asked.join(first, interval).where(F.struct(*KEY, "ln") > F.col("first")).select(*KEY, "ln", "size", "first")
            found = found.unionByName(keep(later, f"d{depth}-later"))
            drop(f"d{depth}-asked", f"d{depth}-first")
            depth *= 2
            if depth > self.min_words or active.where(F.exists("sizes", lambda x: x >= depth)).isEmpty():
                return found
            ahead = active.select(*KEY, (F.col("ln") - depth // 2).alias("ln"), F.col("rank").alias("s"))
            now = active.withColumnRenamed("rank", "r").join(ahead, [*KEY, "ln"])

    def runs(self, documents: DataFrame) -> DataFrame:
        """(doc_id, th, ln, lines, source_id, source_th, source_ln): maximal runs of lines that are copies of an earlier place."""
        copies = self.repeats(documents).withColumn("shift", F.col("ln") - F.col("first.ln"))
        own = (F.col("doc_id") == F.col("first.doc_id")) & (F.col("th") == F.col("first.th"))
        hidden = F.when(own, F.greatest(F.lit(0), F.col("size") - F.col("shift"))).otherwise(0)  # lines that are the original's too
        diagonal = [*KEY, "source_id", "source_th", "shift"]
        spans = copies.select(*KEY, F.col("first.doc_id").alias("source_id"), F.col("first.th").alias("source_th"), "shift", (F.col("ln") + hidden).alias("start"), (F.col("ln") + F.col("size")).alias("stop"))
        order = Window.partitionBy(*diagonal).orderBy("start", "stop")
        spans = spans.withColumn("reach", F.max("stop").over(order.rowsBetween(Window.unboundedPreceding, -1)))
        fresh = F.when(F.col("reach").isNull() | (F.col("start") > F.col("reach")), 1).otherwise(0)
        spans = spans.withColumn("fresh", fresh).withColumn("run", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)))
        merged = spans.groupBy(*diagonal, "run").agg(F.min("start").alias("ln"), F.max("stop").alias("stop"))
        return merged.select(*KEY, "ln", (F.col("stop") - F.col("ln")).alias("lines"), "source_id", "source_th", (F.col("ln") - F.col("shift")).alias("source_ln"))

    def sized(self, runs: DataFrame) -> DataFrame:
        """Maximal runs of the documents last read, with the number of words of each."""
        lines = self.scratch.read("all", LINES).dropDuplicates([*KEY, "ln"]).select(*KEY, F.col("ln").alias("at"), "words")
        each = runs.withColumn("at", F.explode(F.expr("sequence(ln, ln + lines - 1)"))).join(lines, [*KEY, "at"])
        return each.groupBy(*runs.columns).agg(F.sum("words").cast("long").alias("words"))

    def clean(self, documents: DataFrame) -> DataFrame:
        """(doc_id, n_lines, n_deleted, clean_text) of every row."""
        spans = self.runs(documents).select(*KEY, F.explode(F.expr("sequence(ln, ln + lines - 1)")).alias("ln"))
        drops = spans.groupBy(*KEY).agg(F.collect_set("ln").alias("drops"))
        drops = self.scratch.keep(drops, "drops")
        docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("th", F.xxhash64("text"))
        few = drops.agg(F.sum(F.size("drops"))).first()[0] or 0  # deleted lines, four bytes each
        return docs.join(F.broadcast(drops) if few <= BROADCAST_ROWS else drops, KEY, "left").select("doc_id", "text", "drops").mapInArrow(_cleaned, "doc_id long, n_lines long, n_deleted long, clean_text string")


def _hashed(batches):
    for batch in batches:
        text = [hashlib.sha256(x.encode()).hexdigest() for x in batch.column(3).to_pylist()]
        yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(text, pa.string())], names=["doc_id", "n_lines", "n_deleted", "clean_sha256"])


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines and deleted lines of all documents, with a digest of each cleaned text."""
    cleaned = LineRuns(spark).clean(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return cleaned.mapInArrow(_hashed, "doc_id long, n_lines long, n_deleted long, clean_sha256 string")
