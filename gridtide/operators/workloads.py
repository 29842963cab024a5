"""Workloads: hotspots of several shapes over a base stream, drift, query counts."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.config import GridSpec
from gridtide.functions.grid import byte_sum, word

# fixed values: redirected permille for each round of a hotspot
BELL = (20, 80, 200, 320, 400, 400, 320, 200, 80, 20)
STEP = (400,) * 10
HALF_BELL = tuple(v // 2 for v in BELL)
HOT_QUERIES, HOT_SHARE = 100, 20  # extra queries of a hotspot: so many at least, and one for so many of the stream


def hotspot_side(spec: GridSpec, share: float = 0.15) -> int:
    return math.ceil(share * spec.side)


def corner(spec: GridSpec, name: str) -> tuple[int, int]:
    """First cell (cx, cy) of the hotspot square in a corner; cy grows downwards."""
    far = spec.side - hotspot_side(spec)
    return {"lower_left": (0, far), "upper_right": (far, 0), "upper_left": (0, 0), "lower_right": (far, far)}[name]


def permille(start: int, table: tuple[int, ...]) -> Column:
    """The share of redirected points by round, 0 outside the table."""
    out = F.lit(0)
    for k, v in enumerate(table):
        out = F.when(F.col("rnd") == start + k, F.lit(v)).otherwise(out)
    return out


def _place(spec: GridSpec, at: tuple[int, int], shape: str) -> tuple[Column, Column]:
    side = hotspot_side(spec)
    if shape == "uniform":
        return F.lit(at[0]) + word("point_id", "x") % side, F.lit(at[1]) + word("point_id", "y") % side
    z = lambda salt: byte_sum("point_id", salt).cast("double") / 256 - 6
    pos = lambda base, salt: F.greatest(F.lit(0), F.least(F.lit(spec.side - 1), F.lit(base + side // 2) + F.floor(z(salt) * (0.2 * side) + 0.5)))
    return pos(at[0], "n"), pos(at[1], "m")


def redirect(points: DataFrame, spec: GridSpec, spots: list[tuple[str, int, tuple[int, ...]]], shape: str = "uniform") -> DataFrame:
    """Points of which each round's share is moved into hotspots.

    ``spots``: (corner, first round, permille table); simultaneous spots take
    adjoining ranges of the same hash, so together they take the sum of both.
    """
    draw, low = word("point_id", "r") % 1000, F.lit(0)
    cx, cy, hot = F.col("cx"), F.col("cy"), F.lit(False)
    for name, start, table in spots:
        share = permille(start, table)
        take = (draw >= low) & (draw < low + share)
        x, y = _place(spec, corner(spec, name), shape)
        cx, cy, hot = F.when(take, x).otherwise(cx), F.when(take, y).otherwise(cy), hot | take
        low = low + share
    return points.withColumns({"new_cx": cx.cast("int"), "new_cy": cy.cast("int"), "hot": hot}).drop("cx", "cy").withColumnsRenamed({"new_cx": "cx", "new_cy": "cy"})


def hotspot_queries(spark: SparkSession, spec: GridSpec, name: str, start: int, count: int = HOT_QUERIES) -> DataFrame:
    """Extra queries of one cell around hashed places of a hotspot, all registered in its first round."""
    x0, y0 = corner(spec, name)
    side = hotspot_side(spec)
    rows = spark.range(count).select((F.lit(10_000_000) + F.col("id")).alias("query_id"))
    rows = rows.withColumns({"cx": F.lit(x0) + word("query_id", "x") % side, "cy": F.lit(y0) + word("query_id", "y") % side})
    low, high = (lambda c: F.greatest(F.lit(0), F.col(c) - 1).cast("int")), (lambda c: F.least(F.lit(spec.side - 1), F.col(c) + 1).cast("int"))
    return rows.select("query_id", F.lit(start).alias("rnd"), low("cx").alias("cx0"), low("cy").alias("cy0"), high("cx").alias("cx1"), high("cy").alias("cy1"))


SHAPES = {
    "plain": ([], "uniform"),
    "hotspot_uniform": ([("lower_left", 10, BELL)], "uniform"),
    "hotspot_normal": ([("lower_left", 10, BELL)], "normal"),
    "hotspot_step": ([("lower_left", 10, STEP)], "uniform"),
    "hotspot_overlap": ([("lower_left", 10, HALF_BELL), ("upper_right", 10, HALF_BELL)], "uniform"),
    "hotspot_consecutive": ([("lower_left", 8, BELL[1:8]), ("upper_right", 15, BELL[1:8])], "uniform"),
}


def workload(spark: SparkSession, points: DataFrame, queries: DataFrame, spec: GridSpec, name: str) -> tuple[DataFrame, DataFrame]:
    """(points, queries) of a named workload over a base stream."""
    spots, shape = SHAPES[name]
    asked = queries.select("query_id", "rnd", "cx0", "cy0", "cx1", "cy1")
    count = max(HOT_QUERIES, queries.count() // HOT_SHARE) if spots else 0
    for where, start, _ in spots:
        asked = asked.unionByName(hotspot_queries(spark, spec, where, start, count))
    return (redirect(points, spec, spots, shape) if spots else points), asked


def scale_queries(queries: DataFrame, factor: int, spec: GridSpec, at_round: int | None = None) -> DataFrame:
    """Every query ``factor`` times, each copy shifted by a few hashed cells; ``at_round`` -1 has them there before the first round."""
    queries = queries if at_round is None else queries.withColumn("rnd", F.lit(at_round))
    copy = F.explode(F.sequence(F.lit(0), F.lit(factor - 1))).alias("copy")
    rows = queries.select("query_id", "rnd", "cx0", "cy0", "cx1", "cy1", copy).withColumn("query_id", F.col("query_id") * factor + F.col("copy"))
    shift = lambda salt: F.when(F.col("copy") == 0, 0).otherwise(word("query_id", salt) % 5 - 2).cast("int")
    rows = rows.withColumns({"dx": shift("x"), "dy": shift("y")})
    move = lambda c, d: F.greatest(F.lit(0), F.least(F.lit(spec.side - 1), F.col(c) + F.col(d))).cast("int")
    return rows.select("query_id", "rnd", move("cx0", "dx").alias("cx0"), move("cy0", "dy").alias("cy0"), move("cx1", "dx").alias("cx1"), move("cy1", "dy").alias("cy1"))


def drift(points: DataFrame, spec: GridSpec, cells_a_round: int = 1) -> DataFrame:
    """The whole stream wanders to the right, ``cells_a_round`` cells every round."""
    return points.withColumn("cx", F.pmod(F.col("cx") + F.col("rnd") * cells_a_round, F.lit(spec.side)).cast("int"))
