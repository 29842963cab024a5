import random

import pytest
from pyspark.sql import types as T

from gridtide.llm import line_runs as L

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("ln", T.StringType())])


def brute(rows, least):
    """Every run of ``least`` words of any number of lines: all copies but the earliest go, less what lies in it."""
    seq = {}
    for i, t in {(i, t) for i, t, _ in rows if i is not None}:
        seq[i] = [tuple(x.split()) for x in (t or "").split("\n") if x.split()]
    first, drop = {}, {i: set() for i in seq}
    for i in sorted(seq):
        for a in range(len(seq[i])):
            for b in range(a + 1, len(seq[i]) + 1):
                run = tuple(seq[i][a:b])
                if sum(map(len, run)) < least:
                    continue
                j, at = first.setdefault(run, (i, a))
                if (j, at) != (i, a):
                    drop[i] |= set(range(max(a, at + b - a) if i == j else a, b))
    out = {}
    for i, t, _ in rows:
        if i is None:
            continue
        kept, n = [], 0
        for piece in (t or "").splitlines(keepends=True):
            full = bool(piece.split())
            if not (full and n in drop[i]):
                kept.append(piece)
            n += full
        out[i] = (len(seq[i]), len(drop[i]), "".join(kept))
    return out


def corpus(seed):
    rng = random.Random(seed)
    lines = [f"line {i} " + " ".join(f"w{rng.randrange(50)}" for _ in range(rng.choice([1, 4, 20]))) for i in range(25)]
    passage = [f"shared {i} of it" for i in range(14)]
    rows = []
    for d in range(30):
        body = [rng.choice(lines) for _ in range(rng.randrange(0, 9))]
        if rng.random() < 0.5:
            a = rng.randrange(12)
            body[len(body) // 2 : len(body) // 2] = passage[a : a + rng.randrange(2, 14)]
        body = [x + " " * rng.randrange(2) for x in body for x in ([x, ""] if rng.random() < 0.2 else [x])]
        rows.append((d * 3, "\n".join(body), "x"))
    rows += [(500 + i, "\n".join(passage * 3), "x") for i in range(3)]
    rows += [(600, "\n".join(["again and again"] * 20), ""), (601, "\n".join(["again and again"] * 9), "")]
    return rows + [(900, None, None), (901, "", ""), (902, " \n\t\n", ""), (None, "line one\nline two", ""), (903, "é\n" * 60, "")]


@pytest.mark.parametrize("seed,least", [(1, 20), (2, 7), (3, 33)])
def test_equals_brute_force(spark, seed, least):
    rows = corpus(seed)
    got = L.LineRuns(spark, least).clean(spark.createDataFrame(rows, SCHEMA).repartition(3)).collect()
    want = brute(rows, least)
    assert {r.doc_id: (r.n_lines, r.n_deleted, r.clean_text) for r in got if r.doc_id is not None} == want
    assert [r.clean_text for r in got if r.doc_id is None] == ["line one\nline two"]
    assert sum(n for _, n, _ in want.values()) > 20


def test_run_sizes():
    assert L.run_sizes([60, 1, 1], 50) == [[1, 2, 3], [], []]
    assert [sorted(x) for x in L.run_sizes([1, 50, 3], 50)] == [[2], [1, 2], []]
    assert L.run_sizes([10] * 4, 50) == [[], [], [], []] and L.run_sizes([], 50) == []


def test_maximal_runs_take_more_than_two_lines(spark):
    """Twenty short lines are a repeated run of 60 words; two lines of it are none, so depths beyond 2 decide."""
    run = [f"short line {i}" for i in range(20)]
    rows = [(1, "\n".join(["head", *run]), ""), (2, "\n".join(["x", "y", *run, "z"]), ""), (3, "\n".join(run[:2]), ""), (4, "\n".join(run[3:8]), "")]
    frame = spark.createDataFrame(rows, SCHEMA)
    lines = L.LineRuns(spark)
    found = [r.asDict() for r in lines.sized(lines.runs(frame)).collect()]
    assert [(r["doc_id"], r["ln"], r["lines"], r["source_id"], r["source_ln"], r["words"]) for r in found] == [(2, 2, 20, 1, 1, 60)]
    assert {r.doc_id: r.n_deleted for r in L.LineRuns(spark).clean(frame).collect()} == {1: 0, 2: 20, 3: 0, 4: 0}


def test_short_repeats_stay_and_overlaps_keep_the_original(spark):
    line = " ".join(f"w{i}" for i in range(30))
    rows = [(1, "}\n}\nreturn", ""), (2, "}\n}\nelse", ""), (3, "\n".join([line] * 4), "")]
    got = {r.doc_id: r.n_deleted for r in L.LineRuns(spark).clean(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == {1: 0, 2: 0, 3: 2}


def test_repeated_rows_long_lines_and_empty_table(spark):
    long, wide = " ".join(f"w{i}" for i in range(60)), "word  " * 50_000
    rows = [(1, f"a b\n{long}", ""), (1, f"a b\n{long}", ""), (2, f"a b\n{long}\ne", ""), (2, f"other\n{long}", ""), (5, wide, ""), (6, f"x\r\n{wide.strip()}\t\n", "")]
    got = sorted((r.doc_id, r.n_lines, r.n_deleted) for r in L.LineRuns(spark).clean(spark.createDataFrame(rows, SCHEMA)).collect())
    assert got == [(1, 2, 0), (1, 2, 0), (2, 2, 1), (2, 3, 2), (5, 1, 0), (6, 2, 1)]
    assert L.LineRuns(spark).clean(spark.createDataFrame([], SCHEMA)).count() == 0
