"""The pipeline's stages on the given documents, and registered queries against SQL."""

import duckdb
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry_module
import corpus_pipeline
from gridtide.llm import catalog

SF = "/root/testdata/sf0.001"


def test_every_operator_is_registered():
    names = catalog.queries()
    assert sorted(int(n[2:].split("_")[0]) for n in names) == list(range(1, 11))
    assert "pipeline" in entry_module.queries() and len(corpus_pipeline.STAGES) == 5


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_query_equals_sql(spark, name, tmp_path):
    duck = duckdb.connect()
    for table in ("documents", "pages", "conversations"):
        duck.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
    catalog.queries()[name](spark, SF).write.parquet(str(tmp_path / "out"))
    duck.execute(f"CREATE TABLE got AS SELECT * FROM '{tmp_path}/out/*.parquet'")
    duck.execute(f"CREATE TABLE want AS {catalog.oracle_sql()[name]}")
    cols = ", ".join(c[0] for c in duck.execute("DESCRIBE want").fetchall())
    assert set(cols.split(", ")) == {c[0] for c in duck.execute("DESCRIBE got").fetchall()}
    for a, b in (("got", "want"), ("want", "got")):
        assert duck.execute(f"SELECT {cols} FROM {a} EXCEPT ALL SELECT {cols} FROM {b} LIMIT 2").fetchall() == []


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").cache()
    total = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns and 0 < out.count() <= total, name
    distinct = corpus_pipeline.drop_exact_copies(spark, docs, SF)
    assert distinct.select("text").distinct().count() == distinct.count()
    bench = [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    clean = corpus_pipeline.drop_benchmark(spark, docs, SF).collect()
    assert not any(b in r.text for b in bench for r in clean)
    docs.unpersist()


def test_run(spark):
    rows = corpus_pipeline.run(spark, SF)
    assert rows.count() > 0 and {"doc_id", "text", "lang", "source", "n_chars", "mix_pass"} <= set(rows.columns)


def rows_of(frame):
    return sorted(((r.doc_id, r.text, r.note) for r in frame.collect()), key=str)


def test_rows_are_dropped_one_by_one(spark):
    long = " ".join(f"w{i}" for i in range(60))
    bench = spark.read.parquet(f"{SF}/benchmark.parquet").first().text
    rows = [
        (1, "a  b", "stays"), (2, "ab", "exact"), (2, f"another {long}", "stays"), (None, "a b", "exact"), (None, "lone text", "stays"), (3, "same row", "stays"), (3, "same row", "exact"),
        (4, None, "stays"), (5, " ", "longer"), (2, f"{long} tail", "near"), (None, f"{long} other", "near"), (7, bench, "leak"), (7, "nothing leaks here", "stays"), (None, f"x {bench}", "leak"),
    ]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), n) for i, t, n in rows], "doc_id long, text string, lang string, source string, n_chars long, note string")
    exact = rows_of(corpus_pipeline.drop_exact_copies(spark, docs, SF))
    # of the blank texts the longest stays
    assert exact == sorted(((i, t, n) for i, t, n in rows if n != "exact" and i != 4 and not (i == 3 and n == "exact")), key=str)
    near = corpus_pipeline.drop_near_copies(spark, docs, SF)
    texts = [r.text for r in near.collect()]
    assert sum(long in (t or "") for t in texts) == 1 and (2, f"another {long}", "stays") in rows_of(near) or (2, f"{long} tail", "near") in rows_of(near)
    assert texts.count("same row") == 1 and texts.count(None) == 1 and "lone text" in texts
    clean = rows_of(corpus_pipeline.drop_benchmark(spark, docs, SF))
    assert clean == sorted(((i, t, n) for i, t, n in rows if n != "leak"), key=str)


def test_row_ids_are_the_same_in_every_plan(spark, tmp_path):
    from gridtide.llm.store import Scratch, with_row_ids

    spark.range(1000).selectExpr("id % 7 AS file", "id AS row_id").repartition(5).write.parquet(str(tmp_path / "t"))
    frame = spark.read.parquet(str(tmp_path / "t"))
    scratch = Scratch(spark, "test")
    placed = with_row_ids(frame, "_row_id", scratch)
    a = {r.row_id: r["_row_id"] for r in placed.collect()}
    b = {r.row_id: r["_row_id"] for r in placed.select("row_id", "_row_id").repartition(3).collect()}
    assert a == b and len(set(a.values())) == 1000 and placed.columns == ["file", "row_id", "_row_id"]


def test_dropping_tables_trims_the_drivers_native_memory(spark, monkeypatch):
    from gridtide.llm import store

    assert "native heap" in store.trim_native(spark).lower()  # OpenJDK 17.0.9 and later have the command
    told = []
    monkeypatch.setattr(store, "trim_native", told.append)
    scratch = store.Scratch(spark, "trimmed")
    scratch.keep(spark.range(3), "some")
    scratch.drop("some")
    assert told == [spark]


def test_tables_are_written_through_small_arrow_batches(spark):
    from gridtide.llm import store

    def told(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([batch.nbytes])], names=["size"])

    before = spark.conf.get(store.ARROW)
    texts = spark.range(0, 4000, 1, 1).select(F.expr("repeat(cast(id as string), 2000)").alias("text"))
    scratch = store.Scratch(spark, "batches")
    sizes = [r.size for r in scratch.keep(texts.mapInArrow(told, "size long"), "some").collect()]
    assert sum(sizes) > 6 * store.ARROW_BYTES and max(sizes) < 1.1 * store.ARROW_BYTES
    assert spark.conf.get(store.ARROW) == before
    try:
        spark.conf.set(store.ARROW, "1m")  # a lower bound of the session holds
        sizes = [r.size for r in scratch.keep(texts.mapInArrow(told, "size long"), "less").collect()]
        assert max(sizes) < 1.2 * (1 << 20) and spark.conf.get(store.ARROW) in ("1m", "1048576b")
    finally:
        spark.conf.set(store.ARROW, before)
        scratch.close()
    assert [store._byte_count(x) for x in ("64m", "67108864b", "7", "2 KB", "-1b", "1gb")] == [1 << 26, 1 << 26, 7, 2048, -1, 1 << 30]


def test_a_workers_word_tables_are_small(monkeypatch):
    from gridtide.llm import kernel as K

    monkeypatch.setattr(K, "_TABLES", {})
    K.Words(K.Texts(pa.array(["some words " * 300_000]))).hashes()
    assert sum(x.nbytes for x in K._TABLES.values()) <= 32 * K.SEGMENT <= 8 << 20
