import math

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridtide.llm import mixing as M

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("source", T.StringType()), T.StructField("weight", T.StringType())])
ROWS = [(i, "w " * (1 + i % 7), f"s{0 if i < 700 else 1 if i < 900 else 2 if i < 980 else 3}", "x") for i in range(1000)]
ROWS += [(2000, None, "s1", ""), (2001, " ", None, ""), (2002, "", "empty", "")]


def brute_exponent(tokens, flatness, repeats, budget):
    total = sum(tokens)
    p = [t / total for t in tokens]

    def measures(a):
        z = sum(x**a for x in p)
        q = [x**a / z for x in p]
        return -sum(x * math.log(x) for x in q), max(budget * x / y for x, y in zip(q, p))

    def least(enough):
        if enough(*measures(0.0)):
            return 0.0
        low, high = 0.0, 1.0
        for _ in range(30):
            mid = (low + high) / 2
            low, high = (low, mid) if enough(*measures(mid)) else (mid, high)
        return high

    natural = measures(1.0)[0]
    target = natural + flatness * (math.log(len(p)) - natural)
    return max(least(lambda h, _: h <= target + 1e-12), least(lambda _, r: r <= repeats + 1e-12))


@pytest.mark.parametrize("flatness,repeats,budget", [(0.5, 4.0, 1.0), (1.0, 3.0, 1.0), (0.0, 9.0, 2.0), (0.8, 50.0, 0.3)])
def test_weights_budgets_and_copies(spark, flatness, repeats, budget, monkeypatch):
    monkeypatch.setattr(M, "BLOCK_DOCS", 64)
    docs = spark.createDataFrame(ROWS, SCHEMA).repartition(3)
    mixer = M.TemperatureMixer(spark, flatness, repeats, budget)
    tokens = {}
    for _, t, s, _w in ROWS:
        tokens[s or ""] = tokens.get(s or "", 0) + len((t or "").split())
    some = {s: t for s, t in tokens.items() if t}
    want = brute_exponent(list(some.values()), flatness, repeats, budget)
    _, _, exponent = mixer.plan(docs)
    assert abs(exponent - want) < 1e-8
    z = sum((t / sum(some.values())) ** want for t in some.values())
    rows = mixer.assign(docs).select("doc_id", "text", "source", "weight", "_mix.copies", F.col("_mix.weight").alias("w")).collect()
    assert len(rows) == len(ROWS) and {r.weight for r in rows} == {"x", ""}
    spent, least = {}, {}
    for r in rows:
        s = r.source or ""
        spent[s] = spent.get(s, 0) + r.copies * len((r.text or "").split())
        least.setdefault(s, set()).add(r.copies)
        if s in some:
            assert abs(r.w - (some[s] / sum(some.values())) ** want / z) < 1e-6
    for s, t in some.items():
        goal = (t / sum(some.values())) ** want / z * budget * sum(some.values())
        assert goal - 8 <= spent[s] <= goal + 1e-6  # short by less than the document at the edge
        assert max(least[s]) - min(least[s]) <= 1 and max(least[s]) <= math.ceil(repeats)
    assert least["empty"] == {1}


def test_mixture_rows(spark):
    docs = spark.createDataFrame(ROWS, SCHEMA)
    mixer = M.TemperatureMixer(spark)
    copies = {r.doc_id: r.copies for r in mixer.assign(docs).select("doc_id", "_mix.copies").collect()}
    rows = mixer.mix(docs).groupBy("doc_id").agg(F.count("*").alias("n"), F.max("mix_pass").alias("p")).collect()
    assert {r.doc_id: r.n for r in rows} == {i: c for i, c in copies.items() if c}
    assert all(r.n == r.p for r in rows)


def test_edges(spark):
    assert M.TemperatureMixer(spark).mix(spark.createDataFrame([], SCHEMA)).count() == 0
    one = M.TemperatureMixer(spark).assign(spark.createDataFrame([(1, "a b", "s", ""), (1, "a b", "s", ""), (None, "c", "s", "")], SCHEMA)).select("_mix.*").collect()
    assert {r.copies for r in one} == {1} and all(abs(r.weight - 1) < 1e-12 for r in one)
    blank = M.TemperatureMixer(spark).assign(spark.createDataFrame([(1, None, None, None)], SCHEMA)).select("_mix.*").collect()
    assert [(r.copies, r.weight) for r in blank] == [(1, 0.0)]


def test_clashing_columns_stay_as_they_are(spark):
    clashes = "_s _b _mix _mix_source _mix_id _mix_block mix_pass mix_block mix_key mix_row mix_plan mix_rank passes rank file_path".split()
    docs = spark.createDataFrame(ROWS, SCHEMA).withColumns({c: F.lit(f"own {c}") for c in clashes})
    plain = {r.doc_id: tuple(r) for r in M.TemperatureMixer(spark).assign(spark.createDataFrame(ROWS, SCHEMA), ranks=True).select("doc_id", "_mix.copies", "_mix.block", "_mix.rank").collect()}
    got = M.TemperatureMixer(spark).assign(docs, ranks=True)
    assert got.columns == [*docs.columns, "__mix"]
    rows = got.select("*", "__mix.copies", "__mix.block").collect()
    assert all(r[c] == f"own {c}" for r in rows for c in clashes if c != "block")
    assert {r.doc_id: tuple(r.asDict()["__mix"][k] for k in ("copies", "block", "rank")) for r in rows} == {i: v[1:] for i, v in plain.items()}
    mixed = M.TemperatureMixer(spark).mix(docs)
    assert mixed.columns == [*docs.columns, "_mix_pass", "__mix_block", "_mix_key"] and mixed.where("mix_pass <> 'own mix_pass' or mix_key <> 'own mix_key'").count() == 0
    assert mixed.count() == sum(v[1] for v in plain.values())
