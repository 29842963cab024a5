"""Adapters that project the given tables onto points and range queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.config import EVENTS, GridSpec
from gridtide.functions.grid import rectangle_cells, to_cells

EPOCH = "2024-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def event_locations(events: DataFrame) -> DataFrame:
    """Events with x = value, y = k of the JSON properties, and the day as round."""
    return events.select(
        "event_id",
        "ts",
        F.datediff(F.col("ts"), F.lit(EPOCH)).cast("int").alias("rnd"),
        "user_id",
        "event_type",
        F.col("value").alias("x"),
        F.get_json_object("props", "$.k").cast("double").alias("y"),
    )


def event_points(spark: SparkSession, sf_dir: str, spec: GridSpec = EVENTS) -> DataFrame:
    """F1 points: every event that is no signup."""
    rows = event_locations(table(spark, sf_dir, "events").where("event_type <> 'signup'"))
    return to_cells(rows, spec).select(F.col("event_id").alias("point_id"), "ts", "rnd", "x", "y", "cx", "cy", F.col("event_type").alias("tag"))


def event_queries(spark: SparkSession, sf_dir: str, spec: GridSpec = EVENTS, side: int = 2) -> DataFrame:
    """F1 queries: a square of ``side`` cells around every signup."""
    rows = event_locations(table(spark, sf_dir, "events").where("event_type = 'signup'"))
    dx, dy = side / 2 * spec.cell_width, side / 2 * spec.cell_height
    rows = rows.withColumns({"x0": F.col("x") - dx, "x1": F.col("x") + dx, "y0": F.col("y") - dy, "y1": F.col("y") + dy})
    return rectangle_cells(rows, spec).select(
        F.col("event_id").alias("query_id"), F.col("ts").alias("qts"), "rnd", F.col("user_id").alias("subscriber_id"), "x0", "y0", "x1", "y1",
        "cx0", "cy0", "cx1", "cy1", F.lit(None).cast("string").alias("tag"),
    )


def line_points(spark: SparkSession, sf_dir: str, side: int = 64) -> DataFrame:
    """F2 points: line items by price and part, a control without skew."""
    parts = table(spark, sf_dir, "part").count()
    spec = GridSpec(900.0, 0.0, 104101.0, float(parts), side)
    rows = table(spark, sf_dir, "lineitem").select(
        F.struct("l_orderkey", "l_linenumber").alias("point_id"), "l_orderkey", F.col("l_shipdate").alias("ts"), F.col("l_extendedprice").alias("x"), F.col("l_partkey").cast("double").alias("y"), F.col("l_returnflag").alias("tag"),
        ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1).cast("int").alias("rnd"),
    )
    return to_cells(rows, spec)


def order_queries(spark: SparkSession, sf_dir: str, side: int = 64, half: int = 1) -> DataFrame:
    """F2 queries: every order, ``half`` cells around its cell."""
    customers = table(spark, sf_dir, "customer").count()
    spec = GridSpec(1000.0, 0.0, 499001.0, float(customers), side)
    rows = table(spark, sf_dir, "orders").select(
        F.col("o_orderkey").alias("query_id"), F.col("o_orderdate").alias("qts"), F.col("o_custkey").alias("subscriber_id"), F.col("o_totalprice").alias("x"), F.col("o_custkey").cast("double").alias("y")
    )
    low = lambda c: F.greatest(F.lit(0), F.col(c) - half).cast("int")
    high = lambda c: F.least(F.lit(side - 1), F.col(c) + half).cast("int")
    return to_cells(rows, spec).withColumns({"cx0": low("cx"), "cx1": high("cx"), "cy0": low("cy"), "cy1": high("cy")}).withColumn("rnd", F.lit(0))


def embedding_points(spark: SparkSession, sf_dir: str, side: int = 64) -> DataFrame:
    """F3 points: two coordinates of the vectors, a Gaussian blob."""
    spec = GridSpec(-0.5, -0.5, 1.0, 1.0, side)
    rows = table(spark, sf_dir, "embeddings").select(
        F.col("vec_id").alias("point_id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"), F.col("label").cast("string").alias("tag"), F.expr("int(vec_id div 50)").alias("rnd")
    )
    return to_cells(rows, spec)


def embedding_queries(spark: SparkSession, sf_dir: str, side: int = 64, half: int = 1) -> DataFrame:
    """F3 queries: ``half`` cells around every tenth vector, from its round on."""
    rows = embedding_points(spark, sf_dir, side).where(F.col("point_id") % 10 == 0)
    low = lambda c: F.greatest(F.lit(0), F.col(c) - half).cast("int")
    high = lambda c: F.least(F.lit(side - 1), F.col(c) + half).cast("int")
    return rows.select(F.col("point_id").alias("query_id"), F.col("point_id").alias("qts"), "rnd", low("cx").alias("cx0"), low("cy").alias("cy0"), high("cx").alias("cx1"), high("cy").alias("cy1"))


def document_points(spark: SparkSession, sf_dir: str, side: int = 64) -> DataFrame:
    """F4 points: documents by length and a scattered id, with their text as payload."""
    spec = GridSpec(0.0, 0.0, 4096.0, 1000.0, side)
    rows = table(spark, sf_dir, "documents").select(
        F.col("doc_id").alias("point_id"), F.col("n_chars").cast("double").alias("x"), (F.col("doc_id") * 37 % 1000).cast("double").alias("y"), F.col("lang").alias("tag"), "text", F.expr("int(doc_id div 100)").alias("rnd")
    )
    return to_cells(rows, spec)


def replay(points: DataFrame, times: int, rounds: int = 30) -> DataFrame:
    """A finite stream replayed ``times`` times, each pass ``rounds`` rounds (days) later."""
    shift = F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("pass")
    again = points.select("*", shift)
    return again.withColumn("rnd", (F.col("rnd") + F.col("pass") * rounds).cast("int")).withColumn("ts", F.col("ts") + F.make_dt_interval(F.col("pass") * rounds))
