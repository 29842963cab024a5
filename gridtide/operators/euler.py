"""Centralised cell counters: faces, edges and vertices count overlapping queries exactly."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def euler_counts(queries: DataFrame, points: DataFrame | None = None) -> DataFrame:
    """(cx, cy, points, face, v_edge, h_edge, vertex): five counters of each touched cell.

    ``v_edge`` counts queries over the cell and the one to its left, ``h_edge``
    over it and the one above, ``vertex`` over all four around its corner.
    """
    each = queries.withColumn("cx", F.explode(F.sequence("cx0", "cx1"))).withColumn("cy", F.explode(F.sequence("cy0", "cy1")))
    left, top = (F.col("cx") > F.col("cx0")).cast("long"), (F.col("cy") > F.col("cy0")).cast("long")
    counts = each.groupBy("cx", "cy").agg(F.count("*").alias("face"), F.sum(left).alias("v_edge"), F.sum(top).alias("h_edge"), F.sum(left * top).alias("vertex"))
    if points is None:
        return counts
    held = points.groupBy("cx", "cy").agg(F.count("*").alias("points"))
    return counts.join(held, ["cx", "cy"], "full").fillna(0)


def prefix_sums(counts: DataFrame) -> DataFrame:
    """(cx, cy, face, v_edge, h_edge, vertex): sums over all cells up to and including each touched row and column.

    Two running sums: along each column of the grid, then along each row; the
    table has a row for each cell of the touched part of the grid.
    """
    names = ["face", "v_edge", "h_edge", "vertex"]
    box = counts.agg(F.max("cx").alias("w"), F.max("cy").alias("h"))
    grid = box.select(F.explode(F.sequence(F.lit(0), F.col("w"))).alias("cx"), "h").select("cx", F.explode(F.sequence(F.lit(0), F.col("h"))).alias("cy"))
    full = grid.join(counts, ["cx", "cy"], "left").fillna(0, names)
    upto = lambda by, order: Window.partitionBy(by).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    down = full.select("cx", "cy", *(F.sum(c).over(upto("cx", "cy")).alias(c) for c in names))
    return down.select("cx", "cy", *(F.sum(c).over(upto("cy", "cx")).alias(c) for c in names))


def euler_range(counts: DataFrame, ranges: DataFrame) -> DataFrame:
    """(range_id, overlapping) for rectangles: faces less inner edges plus inner vertices.

    Every sum over a rectangle takes four corners of the prefix sums, so a range
    costs sixteen look-ups however large it is.
    """
    sums = prefix_sums(counts)
    edge = F.broadcast(sums.agg(F.max("cx").alias("w"), F.max("cy").alias("h")))
    # each counter has its own rectangle: edges inside the range begin a column or a row later
    parts = [("face", 0, 0, 1), ("v_edge", 1, 0, -1), ("h_edge", 0, 1, -1), ("vertex", 1, 1, 1)]
    looks = F.array(*(
        F.struct(F.lit(name).alias("name"), x.cast("int").alias("cx"), y.cast("int").alias("cy"), F.lit(sign * s).alias("sign"))
        for name, dx, dy, sign in parts
        for x, y, s in (
            (F.col("rx1"), F.col("ry1"), 1), (F.col("rx0") + dx - 1, F.col("ry1"), -1), (F.col("rx1"), F.col("ry0") + dy - 1, -1), (F.col("rx0") + dx - 1, F.col("ry0") + dy - 1, 1)
        )
    ))
    each = ranges.crossJoin(edge).select("range_id", "w", "h", "rx0", "rx1", "ry0", "ry1", F.explode(looks).alias("l")).where("l.cx >= 0 and l.cy >= 0")
    # a range that is one cell wide has no inner edge across: its two look-ups cancel out
    each = each.select("range_id", "l.name", "l.sign", F.least("l.cx", "w").alias("cx"), F.least("l.cy", "h").alias("cy"))
    value = F.when(F.col("name") == "face", F.col("face")).when(F.col("name") == "v_edge", F.col("v_edge")).when(F.col("name") == "h_edge", F.col("h_edge")).otherwise(F.col("vertex"))
    return each.join(sums, ["cx", "cy"]).groupBy("range_id").agg(F.sum(value * F.col("sign")).alias("overlapping"))
