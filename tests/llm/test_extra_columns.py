"""Extra columns with the operators' own names, nulls and empty tables, through every operator and stage."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from gridtide.llm import exact_dedup, license_scan, line_runs, mixing, ngram_join, quality, tiling, toxicity

SF = "/root/testdata/sf0.001"
CLASHES = "row row_id place component file number _row_id mix_pass mix_block mix_key _mix_id _s _b score label n h1 h2 s0 wide sig doc comp root rank depth ln th digest sha kept copies weight block _mix drops a b u v".split()


@pytest.fixture(scope="module")
def docs(spark):
    rows = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([(None, None, None, None, None), (90001, None, "en", None, 0), (90002, "", None, "src0", 0), (90003, " \n ", "en", "src1", 3), (90003, " \n ", "en", "src1", 3)], rows.schema)
    return rows.unionByName(odd).withColumns({c: F.lit("clash") for c in CLASHES}).cache()


def test_operators(spark, docs):
    labels, bench = spark.read.parquet(f"{SF}/labels.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    n = docs.count()
    assert ngram_join.NgramJaccardJoin(spark).run(docs).count() == n
    assert exact_dedup.exact_duplicates(docs).count() == n
    assert quality.score(docs, quality.fit(docs, labels)).count() == n
    assert toxicity.score(docs, toxicity.fit(docs, labels)).count() == n
    assert license_scan.scan(docs).count() == n
    assert line_runs.LineRuns(spark).clean(docs).count() == n
    assert mixing.TemperatureMixer(spark).assign(docs).count() == n
    assert tiling.contamination(docs, bench.withColumn("doc_id", F.lit(1))).count() > 0


def test_stages(spark, docs):
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        assert 0 < out.count(), name
        if name != corpus_pipeline.STAGES[-1][0]:
            assert out.columns == docs.columns, name
        assert stage(spark, docs.limit(0), SF).count() == 0, name
