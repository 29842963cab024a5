"""The bounded, documented sample of labelled rows that classifiers are fitted on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FIT_ROWS = 6000  # labelled documents at most, those of the smallest hash


def remainder(folds: int):
    """crc32 of the document id as text, modulo ``folds``."""
    return F.crc32(F.col("doc_id").cast("string")) % folds


def fit_sample(documents: DataFrame, labels: DataFrame, target: str, folds: int, held: int, rows: int = FIT_ROWS) -> DataFrame:
    """(doc_id, text, label) of at most ``rows`` labelled documents outside the held-out fold.

    A document labelled twice counts once, with the larger label; null ids and
    null labels are left out.
    """
    marked = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(target).cast("int").alias("label")).dropna()
    marked = marked.where(remainder(folds) != held).groupBy("doc_id").agg(F.max("label").alias("label"))
    # a hash first picks about twice as many ids as wanted, so that the sort stays small at any size
    share = min(1.0, 2.0 * rows / max(1, labels.count()) * folds / (folds - 1))
    marked = marked.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < int(share * (1 << 30)))
    few = marked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.join(F.broadcast(few), "doc_id")  # at most ``rows`` rows of two numbers
