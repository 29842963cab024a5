import random
import re

import duckdb
import numpy as np
import pytest
from pyspark.sql import types as T

import __spark_entry__ as entry_module
from gridtide.llm import ngram_join as J

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("n", T.StringType())])


def shingles(text):
    lower = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = [w for w in re.split("[\x20\x09-\x0d]+", lower) if w]
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def brute(rows):
    sets = {i: shingles(t) for i, t, _ in rows if i is not None}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {(i, len(sets[i]), find(i)) for i in sets}


def edited(rng, words, n):
    out = list(words)
    for _ in range(n):
        out[rng.randrange(len(out))] = f"e{rng.randrange(10**6)}"
    return out


def rows_of(seed):
    rng = random.Random(seed)
    rows, ident = [], 0
    for _ in range(14):
        base = [f"w{rng.randrange(4000)}" for _ in range(rng.choice([3, 6, 9, 14, 30, 80, 200, 700]))]
        for _ in range(rng.randrange(1, 7)):
            text = " ".join(edited(rng, base, rng.choice([0, 0, 1, 1, 2, max(1, len(base) // 50)])))
            rows.append((ident, text.upper() if rng.random() < 0.2 else text, "x"))
            ident += rng.randrange(1, 4)
    passage = " ".join(f"p{i}" for i in range(60))
    rows += [(5000 + i, passage + " " + " ".join(f"q{i}_{j}" for j in range(90)), "x") for i in range(12)]
    # a chain whose ends are not similar to each other
    chain = [f"c{i}" for i in range(300)]
    for i in range(8):
        rows.append((7000 - i, " ".join(chain[i * 12 : i * 12 + 200]), "x"))
    return rows + [(9000, None, None), (9001, "", ""), (9002, " \t\n ", ""), (9003, "one", ""), (9004, "ONE", "")]


@pytest.mark.parametrize("seed", [1, 2])
def test_equals_brute_force(spark, seed):
    rows = rows_of(seed)
    found = J.NgramJaccardJoin(spark).run(spark.createDataFrame(rows, SCHEMA).repartition(3))
    assert {tuple(r) for r in found.select("doc_id", "n_shingles", "component_id").collect()} == brute(rows)


def test_repeated_rows_null_ids_and_empty_table(spark):
    rows = [(1, "a b c d e f", "x"), (1, "a b c d e f", "x"), (None, "a b c d e f", None)]
    found = J.NgramJaccardJoin(spark).run(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sorted((r.doc_id or -1, r.n_shingles) for r in found) == [(-1, 2), (1, 2), (1, 2)]
    assert J.NgramJaccardJoin(spark).run(spark.createDataFrame([], SCHEMA)).count() == 0


def test_similar_sets_always_share_a_signature():
    rng = np.random.default_rng(5)
    for size in [1, 2, 3, 4, 5, 7, 8, 9, 15, 17, 31, 33, 60, 100, 130, 255, 260, 500, 900]:
        for _ in range(12):
            x = np.unique(rng.integers(0, 2**63, size, dtype=np.uint64))
            cut = rng.integers(0, max(1, len(x) // 5) + 1)
            y = x[rng.permutation(len(x))[: len(x) - cut]]
            extra = int((len(y) * 100) // 80 - len(x))
            if extra > 0:
                y = np.append(y, rng.integers(0, 2**63, rng.integers(0, extra + 1), dtype=np.uint64))
            y = np.unique(y)
            common = len(np.intersect1d(x, y))
            if 100 * common >= 80 * (len(x) + len(y) - common):
                assert len(np.intersect1d(J.signatures(x), J.signatures(y)))


def test_bands_hold_every_match():
    for size in range(1, 3000):
        _, low, high = J.bands(size)[-1]
        assert low <= size <= high
        partner = size * J.DEN // J.NUM  # the largest set that can match
        number = J.bands(size)[-1][0]
        assert J.bands(partner)[-1][0] in (number, number + 1)
        assert number in [c for c, _, _ in J.classes(partner)] and number in [c for c, _, _ in J.classes(size)]


def test_a_passage_that_many_different_texts_share(spark):
    passage = " ".join(f"p{i}" for i in range(120))
    rows = [(i, f"{passage} " + " ".join(f"q{i}_{j}" for j in range(80)), "x") for i in range(2000)]
    rows += [(5000 + i, rows[i][1] + f" tail{i}", "x") for i in range(0, 2000, 40)]
    found = J.NgramJaccardJoin(spark).run(spark.createDataFrame(rows, SCHEMA).repartition(4))
    assert {(r.doc_id, r.component_id) for r in found.collect()} == {(i, i - 5000 if i >= 5000 else i) for i, _, _ in rows}



@pytest.mark.parametrize("rings", [(J.MEET, J.WIDER, J.CHUNK), (2, 6, 5)])
def test_a_large_group_of_near_copies_lists_few_pairs(spark, monkeypatch, rings):
    for name, value in zip(("MEET", "WIDER", "CHUNK"), rings, strict=True):
        monkeypatch.setattr(J, name, value)
    rng = random.Random(11)
    base = [f"w{i}" for i in range(300)]
    # those of the least ids lead most groups and are similar to few; the others are similar to each other
    rows = [(i, " ".join(edited(rng, base, 8 if i < 80 else 3)), "x") for i in range(800)]
    tried, verify = [], J.NgramJaccardJoin._verify
    monkeypatch.setattr(J.NgramJaccardJoin, "_verify", lambda self, docs, pairs, tag: tried.append(pairs.count()) or verify(self, docs, pairs, tag))
    found = J.NgramJaccardJoin(spark).run(spark.createDataFrame(rows, SCHEMA).repartition(3))
    assert {tuple(r) for r in found.select("doc_id", "n_shingles", "component_id").collect()} == brute(rows)
    assert len(tried) > 2 and sum(tried[2:]) <= 10 * len(rows), tried  # all open pairs are 100 times as many as rows


def brute_links(rows):
    sets = {i: shingles(t) for i, t, _ in rows if i is not None}
    near = lambda a, b: sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])
    return {i: sum(bool(near(i, o)) for o in sets if o != i) for i in sets}


@pytest.mark.parametrize("block", [J.BLOCK, 3])
def test_links_are_exact(spark, monkeypatch, block):
    monkeypatch.setattr(J, "BLOCK", block)
    # near copies that are all similar to each other, two of them twice, beside chains and single texts
    words = [f"t{i}" for i in range(400)]
    group = [" ".join(words[:k] + [f"u{k}"] + words[k + 1 :]) for k in range(20, 400, 40)]
    rows = rows_of(3) + [(20000 + i, t, "x") for i, t in enumerate(group + group[:2])]
    found = J.NgramJaccardJoin(spark).run(spark.createDataFrame(rows, SCHEMA).repartition(3), links=True)
    assert {r.doc_id: r.n_links for r in found.collect()} == brute_links(rows)


def test_links_of_null_and_repeated_ids(spark):
    rows = [(1, "a b c d e f", "x"), (1, "a b c d e f", "x"), (2, "A b c d e f", "x"), (None, "a b c d e f", None)]
    found = J.NgramJaccardJoin(spark).run(spark.createDataFrame(rows, SCHEMA), links=True).collect()
    assert sorted((r.doc_id or -1, r.n_links) for r in found) == [(-1, 0), (1, 1), (1, 1), (2, 1)]


def test_links_equal_sql(spark):
    name, folder = "ngram_jaccard_links", "/root/testdata/sf0.001"
    duck = duckdb.connect()
    duck.execute(f"CREATE VIEW documents AS SELECT * FROM '{folder}/documents.parquet'")
    want = duck.execute(f"SELECT doc_id, n_shingles, component_id, n_links FROM ({entry_module.oracle_sql()[name]})").fetchall()
    found = entry_module.queries()[name](spark, folder).select("doc_id", "n_shingles", "component_id", "n_links").collect()
    assert sorted(tuple(r) for r in found) == sorted(want) and any(r[3] for r in want)
