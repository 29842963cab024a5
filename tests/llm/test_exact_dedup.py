import hashlib
import re

import pytest
from pyspark.sql import types as T

from gridtide.llm import exact_dedup as E

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("digest", T.StringType())])
ROWS = [(1, "a b", "x"), (2, "ab", "x"), (3, "a  b", None), (4, "a\tb ", "y"), (5, None, "z"), (6, "", "z"), (7, " \n", "z"), (8, "é" * 5000, ""), (9, "é " * 5000, ""), (10, "solo", ""), (11, "A b", "")]
ROWS += [(100 + i, "same text", "") for i in range(1200)]


def brute(rows):
    groups = {}
    for i, t, _ in rows:
        groups.setdefault(re.sub("[\x20\x09-\x0d]", "", t or ""), []).append((-len(t or ""), i))
    out = set()
    for body, held in groups.items():
        keep = min(held)[1]
        out |= {(i, keep, len(held), i == keep, hashlib.sha256(body.encode()).hexdigest()) for _, i in held}
    return out


@pytest.mark.parametrize("key_bytes", [32, 1])
def test_equals_brute_force(spark, key_bytes):
    rows = ROWS + [(5000 + i, f"word {i}", "") for i in range(400)] * (key_bytes == 1)
    found = E.exact_duplicates(spark.createDataFrame(rows, SCHEMA).repartition(3), key_bytes=key_bytes)
    assert {tuple(r) for r in found.collect()} == brute(rows)


def test_empty_table_null_ids_and_repeated_rows(spark):
    assert E.exact_duplicates(spark.createDataFrame([], SCHEMA)).count() == 0
    rows = [(1, "q", ""), (1, "q", ""), (None, "q", ""), (None, "lone", ""), (None, "no id", ""), (None, "no id", "")]
    found = sorted((r.doc_id or 0, r.keep_id or 0, r.group_size, r.kept) for r in E.exact_duplicates(spark.createDataFrame(rows, SCHEMA)).collect())
    assert found == [(0, 0, 1, True), (0, 0, 2, False), (0, 0, 2, True), (0, 1, 3, False), (1, 1, 3, False), (1, 1, 3, True)]
    assert {r.text_sha256 for r in E.exact_duplicates(spark.createDataFrame(rows, SCHEMA)).where("kept").collect()} == {hashlib.sha256(t.encode()).hexdigest() for t in ("q", "lone", "noid")}


def test_very_long_texts(spark):
    rows = [(1, "x" * 3_000_000, ""), (2, "x " * 3_000_000, ""), (3, "x" * 2_999_999 + "y", "")]
    assert {tuple(r) for r in E.exact_duplicates(spark.createDataFrame(rows, SCHEMA)).collect()} == brute(rows)


def normal(text):
    return hashlib.sha256(re.sub("[\x20\x09-\x0d]", "", text or "").encode()).digest()


def test_index_over_batches_equals_one_batch(spark):
    index = E.DigestIndex(spark)
    frames = [spark.createDataFrame(ROWS[k::3], SCHEMA) for k in range(3)]
    for frame in frames[:2]:
        index.flush(frame)
    hits = {bytes(r.digest) for r in index.lookup(frames[2]).collect()}
    held, asked = ({normal(t) for _, t, _ in rows} for rows in (ROWS[0::3] + ROWS[1::3], ROWS[2::3]))
    assert hits == held & asked
    index.flush(frames[2])
    index.compact()
    compacted = {(bytes(r.digest).hex(), r.doc_id, r.copies) for r in index.entries().collect()}
    assert compacted == {(sha, keep, n) for _, keep, n, kept, sha in brute(ROWS) if kept}
    assert len(index.tables) == 1
    assert {bytes(r.digest) for r in index.lookup(frames[0]).collect()} == {normal(t) for _, t, _ in ROWS[0::3]}


def test_a_filter_miss_skips_a_run(spark, monkeypatch):
    index = E.DigestIndex(spark, buckets=2)
    index.flush(spark.createDataFrame([(i, f"one {i}", "") for i in range(50)], SCHEMA).coalesce(1))
    index.flush(spark.createDataFrame([(i, f"two {i}", "") for i in range(50)], SCHEMA).coalesce(1))
    asked = spark.createDataFrame([(1, "one 7", "")], SCHEMA)
    may = index.probe(asked).collect()
    assert [r.table for r in may] == [0] and len(may) == 1  # one segment of one run is read, the others are not
    assert [r.doc_id for r in index.lookup(asked).collect()] == [7]
    # in a merge, digests that no filter passes are not searched for
    make = lambda names: E.Segment.collapsed(E._words_of(b"".join(normal(x) for x in names)), *([__import__("numpy").arange(len(names))] * 4), __import__("numpy").ones(len(names), int))
    a, b = make([f"a{i}" for i in range(9)]), make(["b0"])
    searched = []
    monkeypatch.setattr(E.Segment, "find", lambda self, words: searched.append(len(words)) or E.np.full(len(words), -1))
    assert len(a.merge(b)) == 10 and not searched


def test_merging_segments_equals_collapsing_all_at_once():
    import numpy as np

    rng = np.random.default_rng(3)
    for _ in range(40):
        n = int(rng.integers(2, 60))
        words = E._words_of(b"".join(normal(f"t{x}") for x in rng.integers(0, 12, n)))
        cols = [rng.integers(0, 3, n), rng.integers(0, 2, n).astype(np.uint8), rng.permutation(n), rng.integers(0, 3, n), np.ones(n, np.int64)]
        cut = int(rng.integers(1, n))
        whole = E.Segment.collapsed(words, *cols)
        a, b = E.Segment.collapsed(words[:cut], *(c[:cut] for c in cols)), E.Segment.collapsed(words[cut:], *(c[cut:] for c in cols))
        got = a.merge(b)
        for c in ("words", "ids", "absent", "places", "chars", "copies"):
            assert (getattr(got, c) == getattr(whole, c)).all()
