"""Held-out accuracy and edge rows of the trained operators."""

import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import types as T

from gridtide.llm import kernel as K
from gridtide.llm import license_scan, quality, tiling, toxicity

SF = "/root/testdata/sf0.1"
SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("score", T.StringType())])
EDGE = [(1, None, "x"), (2, "", "x"), (3, " \n\t ", "x"), (4, "word", "x"), (4, "word", "x"), (None, "null id", None), (5, "é" * 300000, "x"), (6, "a b " * 60000, "x")]


@pytest.fixture(scope="module")
def labelled(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    return docs, spark.read.parquet(f"{SF}/labels.parquet")


def held_out(spark, rows, labels, target, folds, held):
    want = {r.doc_id: r[target] for r in labels.collect()}
    hits = [(r.predicted, want[r.doc_id]) for r in rows if r.doc_id in want and zlib.crc32(str(r.doc_id).encode()) % folds == held]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % folds == held) for r in rows)
    return hits


def test_quality_on_held_out_rows(spark, labelled):
    rows = quality.op3_quality_classifier(spark, SF).collect()
    hits = held_out(spark, rows, labelled[1], "quality", 5, 0)
    assert np.mean([p == y for p, y in hits]) > 0.97
    assert np.mean([p for p, y in hits if y == 1]) > 0.98


def test_toxicity_on_held_out_rows(spark, labelled):
    rows = toxicity.op8_toxicity(spark, SF).collect()
    hits = held_out(spark, rows, labelled[1], "toxic", 4, 2)
    assert np.mean([p for p, y in hits if y == 1]) > 0.9
    assert np.mean([p for p, y in hits if y == 0]) < 0.01


def test_scores_of_edge_rows(spark, labelled):
    docs, labels = labelled
    frame = spark.createDataFrame(EDGE, SCHEMA)
    q = quality.score(frame, quality.fit(docs, labels, rows=400))
    assert q.columns == [*frame.columns, "_score"]
    got = [r["_score"] for r in q.collect()]
    assert len(got) == len(EDGE) and all(0 <= s <= 1 for s in got) and got[3] == got[4] and got[0] == got[1] == got[2]
    none = quality.fit(docs, labels.limit(0))
    assert {r["_score"] for r in quality.score(frame, none).collect()} == {1.0}
    assert quality.score(spark.createDataFrame([], SCHEMA), none).count() == 0
    plain = toxicity.fit(docs, labels.limit(0))
    tox = toxicity.score(frame, plain).collect()
    assert len(tox) == len(EDGE) and all(0 <= r.score < 0.3 for r in tox)


def test_clauses_are_scored_as_wholes():
    model = toxicity.ToxicityModel(toxicity._fixed_lexicon(), {}, np.array([-3.0, 2.5, 1.0, 0.5, 0.0]), np.zeros(4), np.ones(4)).prepare()
    weigh = lambda t: float(np.expm1(model.features(pa.array([t]))[0, 0]))
    assert weigh("You are an idiot.") > weigh("What an idiot.") > 2.5
    assert weigh("You are not an idiot.") == 0
    assert weigh("They said you are an idiot.") == 0
    assert weigh("They said it. You are an idiot.") > 3
    assert weigh("I will kill you") >= 3 and weigh("bugs kill trees") == 0
    assert weigh("never mind the rest of this long clause about that idiot") > 2.5


def test_words_end_at_punctuation_of_any_script():
    model = toxicity.ToxicityModel(toxicity._fixed_lexicon(), {}, np.array([-3.0, 2.5, 1.0, 0.5, 0.0]), np.zeros(4), np.ones(4)).prepare()
    plain = model.features(pa.array(["you are an idiot"]))[0]
    column = pa.array(["you are an \u201cidiot\u201d", "You are an 'IDIOT'", "\u2026you are an idiot\uff0cok", "you are an idiot\u2014so", "you are an\u00a0idiot", None, "", "’"])
    got = model.features(column)
    assert (got[:5, 0] == plain[0]).all() and not got[5:].any()
    assert model.features(pa.array(["you don\u2019t idiot"]))[0, 0] == 0 < model.features(pa.array(["don\u3002idiot you"]))[0, 0]


def test_learning_and_scoring_fold_alike(spark):
    rows = [(i, f"{'\u00c4RGERWORT' if i % 2 else 'Sch\u00f6n'} \u201ew{i}\u201c", i % 2) for i in range(400)]
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels).prepare()
    hot, cold = model.features(pa.array(["das ist \u00e4rgerwort", "\u201e\u00c4rgerwort\u201c", "sch\u00f6n", "SCH\u00d6N."]))[:, 0].reshape(2, 2)
    assert (hot > 0).all() and not cold.any()


def test_transducers_compose_like_running_one_after_another():
    rng = np.random.default_rng(1)
    machines = [toxicity.negation(), toxicity.reported(), toxicity.clause_grammar()]
    whole = toxicity.grammar()
    for _ in range(200):
        tape = rng.integers(0, 10, 12).tolist()
        one, state = 0.0, 0
        for x in tape:
            state, _, w = whole.arcs[state, x]
            one += w
        for m in machines:
            out, state, total = [], 0, 0.0
            for x in tape:
                state, y, w = m.arcs[state, x]
                out.append(y)
                total += w
            tape = out
        assert one == total


def test_licences(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = license_scan.fit(docs)
    rows = [(1, "Some text here.\nReleased under the MIT License.\nmore", ""), (2, "Licensed under the Apache License, Version 2.0.", ""), (3, "the driver lost his license yesterday", ""), (4, "prose without anything\n" * 50, ""), (7, "long " * 500 + "This work is licensed under the GNU General Public License, version 3. " + "tail " * 500, "")]
    got = license_scan.scan(spark.createDataFrame(rows + [(10 + (i or 0), t, s) for i, t, s in EDGE], SCHEMA), model)
    found = {r.doc_id: r.families for r in got.collect()}
    assert (found[1], found[2], found[3], found[4], found[7]) == ("MIT", "Apache-2.0", None, None, "GPL")
    assert all(found[i] is None for i in found if i >= 10)
    assert license_scan.scan(spark.createDataFrame([], SCHEMA), model).count() == 0


# fixed values: the notices that the given tables hold, as whole lines
NOTICES = {
    "This work is licensed under the GNU General Public License, version 3.": "GPL", "All rights reserved.": "proprietary", "Released under the MIT License.": "MIT",
    "Licensed under CC BY-NC 4.0.": "CC-BY-NC", "Licensed under the Apache License, Version 2.0.": "Apache-2.0",
}


def test_licences_of_all_notices_in_the_tables(spark):
    """Recall and precision over every document, against a plain search for the notices."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    want = {r.doc_id: {f for line in (r.text or "").split("\n") for n, f in NOTICES.items() if n in line} for r in docs.collect()}
    got = {r.doc_id: set((r.families or "").split(",")) - {""} for r in license_scan.scan(docs).collect()}
    pairs = lambda d: {(i, f) for i, s in d.items() for f in s}
    hit = len(pairs(want) & pairs(got))
    assert hit / len(pairs(want)) > 0.98 and hit / len(pairs(got)) > 0.98, (hit, len(pairs(want)), len(pairs(got)), sorted(pairs(want) ^ pairs(got))[:5])


@pytest.mark.parametrize("family,text", license_scan.TEMPLATES)
def test_every_template_is_found_among_prose(licences, family, text):
    spark, model = licences
    rows = [(1, f"Some prose stands before.\n{text}\nand more behind.", "")]
    assert license_scan.scan(spark.createDataFrame(rows, SCHEMA), model).first().families == family


@pytest.fixture(scope="module")
def licences(spark):
    return spark, license_scan.fit(spark.read.parquet("/root/testdata/sf0.01/documents.parquet"))


def brute_tiles(doc, item, least):
    """Greedy tiling by its definition: the longest free common run, again and again."""
    free_d, free_i, out = [True] * len(doc), [True] * len(item), []
    while True:
        best = (least - 1, 0, 0)
        for j in range(len(item)):
            for i in range(len(doc)):
                n = 0
                while i + n < len(doc) and j + n < len(item) and doc[i + n] == item[j + n] and free_d[i + n] and free_i[j + n]:
                    n += 1
                if n > best[0]:
                    best = (n, i, j)
        if best[0] < least:
            return sum(n for n, _, _ in out)
        n, i, j = best
        out.append(best)
        for k in range(n):
            free_d[i + k] = free_i[j + k] = False


@pytest.mark.parametrize("seed", range(25))
def test_tiling_equals_its_definition(seed):
    rng = np.random.default_rng(seed)
    item = [f"t{x}" for x in rng.integers(0, 12, 40)]
    parts = [item[a : a + n] for a, n in zip(rng.integers(0, 35, 5), rng.integers(3, 20, 5))]
    doc = [w for p in parts for w in [*p, *(f"x{v}" for v in rng.integers(0, 9, 2))]]
    seeds = tiling.Seeds([7], [" ".join(item)])
    hashes, first = tiling.token_hashes(pa.array(["", " ".join(doc), None]))
    found = list(seeds.search(hashes, first))
    want = brute_tiles(doc, item, tiling.MIN_MATCH)
    assert (found[0][4] if found else 0) == want


def test_junk_that_repeats_a_token_takes_linear_memory():
    import tracemalloc

    seeds = tiling.Seeds([1, 2], ["a " * 200, "a b " * 100])
    hashes, first = tiling.token_hashes(pa.array(["a " * 300_000, "a b " * 150_000, "\u00e9\u2014" * 1000]))
    tracemalloc.start()
    found = list(seeds.search(hashes, first))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found == [(0, 1, 1.0, 1, 200), (1, 2, 1.0, 1, 200)] and peak < 100 << 20


@pytest.mark.parametrize("seed", range(10))
def test_tiling_of_few_tokens_equals_its_definition(seed):
    rng = np.random.default_rng(seed + 100)
    item, doc = ([f"t{x}" for x in rng.integers(0, 2, n)] for n in (24, 60))
    seeds = tiling.Seeds([7], [" ".join(item)])
    hashes, first = tiling.token_hashes(pa.array([" ".join(doc), "x"]))
    found = list(seeds.search(hashes, first))
    assert (found[0][4] if found else 0) == brute_tiles(doc, item, tiling.MIN_MATCH)


def test_tokens_end_at_punctuation_of_any_script(spark):
    words = "uno dos tres cuatro cinco seis siete ocho"
    bench = spark.createDataFrame([(1, words)], "item_id long, text string")
    doc = words.upper().replace(" ", "\u2014").replace("TRES", "\u201cTRES\u201d")
    assert [r.coverage for r in tiling.contamination(spark.createDataFrame([(5, doc)], "doc_id long, text string"), bench).collect()] == [1.0]


def test_long_words_and_segments(monkeypatch):
    texts = pa.array(["ab cd " * 50, "x" * 500 + " y", "", "\u00e9t\u00e9 " * 30])
    whole = K.Words(K.Texts(texts)).hashes()
    monkeypatch.setattr(K, "SEGMENT", 16)
    assert (K.Words(K.Texts(texts)).hashes() == whole).all() and len(np.unique(whole)) == 5


def test_reordered_passages_are_caught(spark):
    a, b, c = (" ".join(f"{k}{i}" for i in range(12)) for k in "abc")
    bench = spark.createDataFrame([(1, f"{a} {b} {c}"), (2, "too short"), (3, None), (1, f"{a} {b} {c}")], "item_id long, text string")
    rows = [(1, f"noise {c.upper()}, more; {a} {b}!", ""), (2, f"{a} only", ""), (3, "x " * 100, ""), *[(10 + (i or 0), t, s) for i, t, s in EDGE]]
    got = {(r.doc_id, r.item_id, r.coverage) for r in tiling.contamination(spark.createDataFrame(rows, SCHEMA), bench).collect()}
    assert got == {(1, 1, 1.0)}
    assert tiling.contamination(spark.createDataFrame([], SCHEMA), bench).count() == 0
    assert tiling.contamination(spark.createDataFrame(rows, SCHEMA), bench.limit(0)).count() == 0


def test_benchmark_in_slices_gives_the_same(spark, monkeypatch):
    docs, bench = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/benchmark.parquet")
    one = sorted(map(tuple, tiling.contamination(docs, bench).collect()))
    monkeypatch.setattr(tiling, "SLICE_BYTES", 3000)
    assert sorted(map(tuple, tiling.contamination(docs, bench).collect())) == one and one


def test_word_kernel_against_regex():
    import re

    texts = ["", None, "a", " a  b\tc\n", "Ünï cödé  x", "A" * 70 + " b", "\x0b\x0c\r"]
    words = K.Words(K.Texts(pa.array(texts)))
    for i, t in enumerate(texts):
        got = [bytes(words.data[a:b]).decode() for a, b in zip(words.starts[words.first[i] : words.first[i + 1]], words.ends[words.first[i] : words.first[i + 1]])]
        assert got == [w for w in re.split("[\x20\x09-\x0d]+", t or "") if w]
    assert K.word_hash("AbC") == K.word_hash("abc") != K.word_hash("abd")
