"""Routing of points and range queries to tiles and machines."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridtide.functions.grid import holds, overlaps
from gridtide.plans.layout import Tile, probe_side, small

SMALL_PLAN = 4096  # tiles up to which a plan is probed by bounds
CELLS_MOST = 4_000_000  # rows of a cell table that are broadcast at most (16 bytes each)


def cell_table(plan: DataFrame) -> DataFrame:
    """(cx, cy, tile_id, machine_id): one row for each cell of the grid."""
    rows = plan.select("tile_id", "machine_id", "cy0", "cy1", F.explode(F.sequence("cx0", "cx1")).alias("cx"))
    return rows.select("cx", F.explode(F.sequence("cy0", "cy1")).alias("cy"), "tile_id", "machine_id")


def route_points(points: DataFrame, plan: DataFrame, method: str = "probe") -> DataFrame:
    """Each point with its tile and machine; exactly one tile holds it.

    ``probe`` joins on the tile bounds (a plan of few tiles, broadcast);
    ``lookup`` joins on the cell, broadcast up to CELLS_MOST cells and shuffled
    beyond; ``auto`` counts the tiles and takes the one or the other.
    """
    if method == "auto":
        method = "probe" if plan.count() <= SMALL_PLAN else "lookup"
    if method == "probe":
        return points.join(small(probe_side(plan)), holds()).drop("t_cx0", "t_cy0", "t_cx1", "t_cy1")
    if method == "lookup":
        cells = plan.agg(F.sum((F.col("cx1") - F.col("cx0") + 1).cast("long") * (F.col("cy1") - F.col("cy0") + 1))).first()[0] or 0
        return points.join(F.broadcast(cell_table(plan)) if cells <= CELLS_MOST else cell_table(plan), ["cx", "cy"])
    raise ValueError(method)


def route_queries(queries: DataFrame, plan: DataFrame, method: str = "join", tiles: list[Tile] | None = None, entry: str = "clipped_corner") -> DataFrame:
    """Each query once for every tile that it overlaps.

    ``join`` tests bounds; ``cells`` visits every covered cell; ``hop`` goes
    from tile to tile over their borders (``tiles`` needed).  With ``entry``
    set to first_met the walk goes on from the cell where a tile was met, which
    can miss tiles and is kept for comparison.
    """
    if method == "join":
        return queries.join(small(probe_side(plan)), overlaps()).drop("t_cx0", "t_cy0", "t_cx1", "t_cy1")
    if method == "cells":
        each = queries.withColumn("cx", F.explode(F.sequence("cx0", "cx1"))).withColumn("cy", F.explode(F.sequence("cy0", "cy1")))
        return each.join(small(cell_table(plan)), ["cx", "cy"]).drop("cx", "cy").distinct()
    if method != "hop":
        raise ValueError(method)
    walk = border_walk(tiles, entry)
    schema = T.StructType([*queries.schema.fields, T.StructField("tile_id", T.LongType()), T.StructField("machine_id", T.IntegerType())])

    def run(frames):
        for frame in frames:
            found = [walk(*r) for r in frame[["cx0", "cy0", "cx1", "cy1"]].itertuples(index=False)]
            out = frame.loc[frame.index.repeat([len(f) for f in found])].copy()
            out["tile_id"] = pd.Series([t for f in found for t, _ in f], index=out.index, dtype="int64")
            out["machine_id"] = pd.Series([m for f in found for _, m in f], index=out.index, dtype="int32")
            yield out

    return queries.mapInPandas(run, schema)


def cell_index(tiles: list[Tile]) -> np.ndarray:
    """Dense cell -> position in ``tiles`` array of the routing layer."""
    side = 1 + max(max(t.cx1, t.cy1) for t in tiles)
    grid = np.full((side, side), -1, np.int32)
    for i, t in enumerate(tiles):
        grid[t.cx0 : t.cx1 + 1, t.cy0 : t.cy1 + 1] = i
    return grid


def border_walk(tiles: list[Tile], entry: str = "clipped_corner"):
    """A function from a cell rectangle to its (tile, machine) pairs, one look-up for each piece of a tile.

    The tile under a rectangle's first corner is peeled off, which leaves what
    lies to the right of it and what lies below; both are worked on alike, so
    no part of the rectangle stays unseen.  ``first_met`` instead follows the
    right and lower neighbours of the cell in which a tile was met.
    """
    grid = cell_index(tiles)
    edge = grid.shape[0] - 1
    names = [(t.tile_id, t.machine_id) for t in tiles]

    def peel(cx0: int, cy0: int, cx1: int, cy1: int) -> list[tuple[int, int]]:
        seen = set()
        rest = [(cx0, cy0, min(cx1, edge), min(cy1, edge))]
        for left, top, right, bottom in rest:  # grows while it is read
            i = int(grid[left, top])
            seen.add(i)
            far, low = min(tiles[i].cx1, right), min(tiles[i].cy1, bottom)
            if far < right:
                rest.append((far + 1, top, right, low))
            if low < bottom:
                rest.append((left, low + 1, right, bottom))
        return [names[i] for i in sorted(seen)]

    def neighbours(cx0: int, cy0: int, cx1: int, cy1: int) -> list[tuple[int, int]]:
        seen = set()

        def visit(x: int, y: int) -> None:
            if x <= min(cx1, edge) and y <= min(cy1, edge) and (i := int(grid[x, y])) not in seen:
                seen.add(i)
                visit(x, tiles[i].cy1 + 1)
                visit(tiles[i].cx1 + 1, y)

        visit(cx0, cy0)
        return [names[i] for i in sorted(seen)]

    return {"clipped_corner": peel, "first_met": neighbours}[entry]


def deliver(routed: DataFrame, plan: DataFrame) -> DataFrame:
    """Tile bounds attached by id: what a machine's own table of tiles answers."""
    return routed.drop("machine_id").join(small(probe_side(plan)), "tile_id")


def place(frame: DataFrame, machines: int) -> DataFrame:
    """One Spark partition for each machine."""
    return frame.repartitionById(machines, "machine_id")


def router_of(frame: DataFrame, ident: str, routers: int) -> DataFrame:
    """The one router through which each object enters."""
    return frame.withColumn("router", F.pmod(F.col(ident), F.lit(routers)).cast("int"))


def route_with_lag(points: DataFrame, history: DataFrame, lag: int = 1) -> DataFrame:
    """Points routed by a plan ``lag`` rounds old and forwarded where the owner has changed.

    ``history`` holds a plan for each round.  Each point is evaluated once, by
    its owner under the current plan; ``forwarded`` tells that the router sent
    it to an earlier owner first.
    """
    plans = history.selectExpr("round", "tile_id", "machine_id", "cx0 AS t_cx0", "cy0 AS t_cy0", "cx1 AS t_cx1", "cy1 AS t_cy1")
    now = points.join(small(plans), (F.col("round") == F.col("rnd")) & holds()).drop("round", "t_cx0", "t_cy0", "t_cx1", "t_cy1")
    old = plans.selectExpr("round AS old_round", "machine_id AS sent_to", "t_cx0", "t_cy0", "t_cx1", "t_cy1")
    both = now.join(small(old), (F.col("old_round") == F.greatest(F.lit(0), F.col("rnd") - lag)) & holds())
    return both.withColumn("forwarded", F.col("sent_to") != F.col("machine_id")).drop("old_round", "t_cx0", "t_cy0", "t_cx1", "t_cy1")


def route_queries_by_round(queries: DataFrame, history: DataFrame) -> DataFrame:
    """Each query once for every tile that it overlaps in the plan of its round."""
    plans = history.selectExpr("round", "tile_id", "machine_id", "cx0 AS t_cx0", "cy0 AS t_cy0", "cx1 AS t_cx1", "cy1 AS t_cy1")
    return queries.join(small(plans), (F.col("round") == F.col("rnd")) & overlaps()).drop("round", "t_cx0", "t_cy0", "t_cx1", "t_cy1")
