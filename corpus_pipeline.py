"""A corpus pipeline: quality, exact and near duplicates, benchmark passages, mixture.

Each stage takes ``(spark, docs, sf_dir)`` and returns the documents that it
keeps, all but the last with the columns it was given.  Stages decide and drop
row by row, never by id: rows that share an id, or have none, are judged each by
its own text.  Null and blank texts are equal to each other and near to nothing;
columns beyond those of ``documents`` go along, whatever their names; an empty
table stays empty.  ``run`` writes every stage's result as Parquet and hands the
reread table on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.llm import exact_dedup, mixing, ngram_join, quality, tiling
from gridtide.llm.store import Scratch, bounded, free_name, scratches, with_row_ids


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that the quality classifier rejects; it learns from the input's labelled rows."""
    model = quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scored = quality.score(docs, model)
    return scored.where(F.col(scored.columns[-1]) >= quality.THRESHOLD).select(*docs.columns)


def drop_exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one row of each group of texts that are equal but for blanks: the longest, then the one of the least id."""
    scratch, row = Scratch(spark, "stage-exact"), free_name(docs.columns, "row_id")
    placed = with_row_ids(docs, row, scratch)
    gone = exact_dedup.exact_duplicates(placed, row=row).where(~F.col("kept"))
    return _without(docs, placed, row, gone.select(row), scratch)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one row of each component of near-duplicate links: that of the least id."""
    scratch, row = Scratch(spark, "stage-near"), free_name(docs.columns, "row_id")
    placed = with_row_ids(docs, row, scratch)
    found = ngram_join.NgramJaccardJoin(spark).run(placed.select(F.col(row).alias("doc_id"), "text"))
    linked = found.where("doc_id <> component_id").select(F.col("doc_id").alias(row), F.col("component_id").alias("component"))
    roots = linked.select(F.col("component").alias(row), "component").distinct()
    members = scratch.keep(linked.unionByName(roots), "members")
    known = placed.select(row, F.col("doc_id").alias("doc_id")).join(bounded(members), row)
    first = F.min(F.struct(F.col("doc_id").isNull(), F.col("doc_id"), F.col(row).alias("row"))).alias("first")
    stay = scratch.keep(known.groupBy("component").agg(first).select(F.col("first.row").alias(row)), "stay")
    return _without(docs, placed, row, members.select(row).join(stay, row, "left_anti"), scratch)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop rows that hold a benchmark passage."""
    scratch, row = Scratch(spark, "stage-leaks"), free_name(docs.columns, "row_id")
    placed = with_row_ids(docs, row, scratch)
    found = tiling.contamination(placed.select(F.col(row).alias("doc_id"), "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return _without(docs, placed, row, found.select(F.col("doc_id").alias(row)).distinct(), scratch)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The temperature mixture of what is left, with each copy's place."""
    return mixing.TemperatureMixer(spark).mix(docs)


def _without(docs: DataFrame, placed: DataFrame, row: str, gone: DataFrame, scratch: Scratch) -> DataFrame:
    rows = scratch.keep(gone, "gone")
    return placed.join(bounded(rows), row, "left_anti").select(*(F.col(f"`{c}`") for c in docs.columns))


STAGES = [
    ("quality", keep_good),
    ("exact", drop_exact_copies),
    ("near", drop_near_copies),
    ("benchmark", drop_benchmark),
    ("mixture", mix),
]
ORACLE_SQL = None  # trained and iterative stages; tests hold each against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage has left behind is deleted once its result is written."""
    scratch = Scratch(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        with scratches():
            docs = scratch.keep(stage(spark, docs, sf_dir), f"{k}-{name}")
        if k:
            scratch.drop(f"{k - 1}-{STAGES[k - 1][0]}")
    return docs
