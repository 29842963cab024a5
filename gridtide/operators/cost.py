"""Costs of tiles and machines."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def tile_cost(stats: DataFrame) -> DataFrame:
    """Cost numerator of each tile: points x queries x recent arrivals, beyond the range of a long."""
    whole = "decimal(38,0)"
    exact = F.col("n").cast(whole) if dict(stats.dtypes)["n"] == "bigint" else None
    product = F.col("n") * F.col("q").cast("double") * F.col("r").cast("double")
    if exact is not None:
        product = (F.col("n").cast("decimal(12,0)") * F.col("q").cast("decimal(12,0)") * F.col("r").cast("decimal(12,0)")).cast(whole)
    return stats.withColumn("numerator", product)


def arrival_share(stats: DataFrame) -> DataFrame:
    """Share of the round's arrivals that each tile got; the table has a row for each tile."""
    return stats.withColumn("share", F.col("r") / F.sum("r").over(Window.partitionBy(F.lit(0))))


def machine_report(stats: DataFrame) -> DataFrame:
    """The two numbers that a machine reports: its numerator and its arrivals."""
    return stats.groupBy("machine_id").agg(F.sum("numerator").alias("numerator"), F.sum("r").alias("r"))


def report_rollup(stats: DataFrame) -> DataFrame:
    """Arrivals and numerators of tiles, machines and the system in one pass."""
    return stats.rollup("machine_id", "tile_id").agg(F.sum("numerator").alias("numerator"), F.sum("r").alias("r"))


def rank_machines(report: DataFrame) -> DataFrame:
    """Machines by cost, the larger first, ties by id; the report has a row for each machine."""
    total = F.sum("r").over(Window.partitionBy(F.lit(0)))
    place = F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("numerator"), "machine_id"))
    return report.withColumn("place", place).withColumn("cost", F.col("numerator").cast("double") / total)
