"""Layouts and strategies that the adaptive method is compared with."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.config import BalanceConfig, GridSpec
from gridtide.operators import rounds as R
from gridtide.plans.layout import Tile, even_layout, plan_frame

HISTORY_MOST = 400_000  # history points at most; half as many queries


def _cut_costs(points: np.ndarray, rects: np.ndarray, tile: Tile, axis: str) -> tuple[np.ndarray, np.ndarray]:
    """Cost of both parts for each line of a tile; cost = points x queries x (points + queries)."""
    part = points[tile.cx0 : tile.cx1 + 1, tile.cy0 : tile.cy1 + 1]
    along = part.sum(axis=0) if axis == "row" else part.sum(axis=1)
    low, high = (tile.cy0, tile.cy1) if axis == "row" else (tile.cx0, tile.cx1)
    a, b = (1, 3) if axis == "row" else (0, 2)
    hit = rects[(rects[:, 0] <= tile.cx1) & (rects[:, 2] >= tile.cx0) & (rects[:, 1] <= tile.cy1) & (rects[:, 3] >= tile.cy0)]
    size = high - low + 1
    first = np.cumsum(np.bincount(np.maximum(hit[:, a], low) - low, weights=hit[:, 4], minlength=size))
    ended = np.cumsum(np.bincount(np.minimum(hit[:, b], high) - low, weights=hit[:, 4], minlength=size))
    n, total = np.cumsum(along), hit[:, 4].sum()
    n1, q1 = n[:-1].astype(float), first[:-1]
    n2, q2 = n[-1] - n1, total - ended[:-1]
    return n1 * q1 * (n1 + q1), n2 * q2 * (n2 + q2)


def _cost(points: np.ndarray, rects: np.ndarray, t: Tile) -> float:
    n = float(points[t.cx0 : t.cx1 + 1, t.cy0 : t.cy1 + 1].sum())
    hit = (rects[:, 0] <= t.cx1) & (rects[:, 2] >= t.cx0) & (rects[:, 1] <= t.cy1) & (rects[:, 3] >= t.cy0)
    q = float(rects[hit, 4].sum())
    return n * q * (n + q)


def history_layout(points: DataFrame, queries: DataFrame, spec: GridSpec, machines: int, most: int | None = HISTORY_MOST) -> list[Tile]:
    """Tiles of nearly equal cost on a history: the dearest tile is cut at its most even line.

    The history is the first ``most`` points and half as many queries, or all
    of both where ``most`` is None; what reaches the driver is their count by
    cell and by rectangle.
    """
    if most is not None:
        points, queries = points.orderBy("ts", "point_id").limit(most), queries.orderBy("qts", "query_id").limit(most // 2)
    cells = points.groupBy("cx", "cy").agg(F.count("*").alias("n")).collect()
    boxes = queries.groupBy(*R.RECT).agg(F.count("*").alias("n")).collect()
    grid = np.zeros((spec.side, spec.side))
    for r in cells:
        grid[r["cx"], r["cy"]] = r["n"]
    return even_cost_layout(grid, np.array([tuple(r) for r in boxes], dtype=np.int64).reshape(-1, 5), spec, machines)


def even_cost_layout(grid: np.ndarray, rects: np.ndarray, spec: GridSpec, machines: int) -> list[Tile]:
    """Tiles of nearly equal cost from points by cell and (rectangle, queries) rows."""
    tiles, fresh = [Tile(0, 0, 0, 0, spec.side - 1, spec.side - 1)], 1
    while len(tiles) < machines:
        big = [t for t in tiles if t.area > 1]
        if not big:
            break
        t = max(big, key=lambda t: (_cost(grid, rects, t), -t.tile_id))
        options = []
        for k, axis in enumerate(("row", "col")):
            c1, c2 = _cut_costs(grid, rects, t, axis)
            options += [(abs(a - b), k, i) for i, (a, b) in enumerate(zip(c1, c2, strict=True))]
        _, k, after = min(options)
        tiles.remove(t)
        for bounds in t.cut(("row", "col")[k], after):
            tiles.append(Tile(fresh, 0, *bounds))
            fresh += 1
    tiles.sort(key=lambda t: (t.cx0, t.cy0))
    return [Tile(t.tile_id, i, t.cx0, t.cy0, t.cx1, t.cy1) for i, t in enumerate(tiles)]


def layout_costs(points: DataFrame, queries: DataFrame, tiles: list[Tile]) -> DataFrame:
    """(machine_id, cost) of a layout on a history that counts as one round."""
    spark = points.sparkSession
    stream = R.Stream(points.groupBy("cx", "cy").agg(F.count("*").alias("points")).withColumn("rnd", F.lit(0)), queries.groupBy(*R.RECT).agg(F.count("*").alias("queries")).withColumn("rnd", F.lit(0)), 1)
    return R.reports(R.tile_stats(stream, plan_frame(spark, tiles), 0, 1.0)).select("machine_id", F.col("numerator").alias("cost"))


def default_capacity(stream: R.Stream, tiles: list[Tile], machines: int, executor: str = "scan") -> float:
    """Checks a machine can do in a round: 1.25 times the history layout's mean load."""
    config = BalanceConfig(machines=machines, executor=executor)
    run = R.static_run(R.static_loads(stream, plan_frame(stream.cells.sparkSession, tiles)), stream, "history_grid", len(tiles), config)
    return 1.25 * (sum(r["mean_load"] for r in run.rows) / max(1, len(run.rows)) or 1.0)


def static_runs(spark: SparkSession, stream: R.Stream, history: list[Tile], spec: GridSpec, config: BalanceConfig, replicas: int | None = None) -> list[R.Run]:
    """The strategies that never change: replicated (on ``replicas`` machines), uniform grid, history grid."""
    uniform, many = even_layout(spec, config.machines), replace(config, machines=replicas or config.machines)
    return [
        R.static_run(R.replicated_loads(stream, many.machines), stream, "replicated", many.machines, many),
        R.static_run(R.static_loads(stream, plan_frame(spark, uniform)), stream, "uniform_grid", len(uniform), config),
        R.static_run(R.static_loads(stream, plan_frame(spark, history)), stream, "history_grid", len(history), config),
    ]


def compare(spark: SparkSession, stream: R.Stream, history: list[Tile], spec: GridSpec, config: BalanceConfig, policies=("lazy",)) -> list[R.Run]:
    """All strategies on one stream: replicated, uniform grid, history grid, adaptive."""
    plays = [(stream, replace(config, policy=p), None) for p in policies]
    return static_runs(spark, stream, history, spec, config) + R.adaptive_all(spark, spec, plays)


def halt_and_replan(spark: SparkSession, points: DataFrame, queries: DataFrame, spec: GridSpec, machines: int, rounds: list[int] | None = None) -> list[tuple[int, list[Tile]]]:
    """Centralised repartitioning: at the end of each round (or of the given ones) stop and lay out all history anew.

    The centre adds up each round's counts by cell and by rectangle, so a round
    sends its own counts only; the layout is of everything up to then.
    """
    stream = R.counted(spark, points, queries)
    grid, rects, out = np.zeros((spec.side, spec.side)), {}, []
    for rnd in range(-1, stream.rounds):
        for r in stream.cells.where(F.col("rnd") == rnd).collect():  # bounded by the grid
            grid[r["cx"], r["cy"]] += r["points"]
        for r in stream.rects.where(F.col("rnd") == rnd).collect():  # a round's rectangles
            box = tuple(r[c] for c in R.RECT)
            rects[box] = rects.get(box, 0) + r["queries"]
        if rnd >= 0 and (rounds is None or rnd in rounds):
            out.append((rnd, even_cost_layout(grid, np.array([(*b, n) for b, n in rects.items()], dtype=np.int64).reshape(-1, 5), spec, machines)))
    return out
