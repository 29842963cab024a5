"""Measures over rounds, loads and plans."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridtide.config import GridSpec
from gridtide.functions.grid import cell_of
from gridtide.operators.matching import match_continuous
from gridtide.operators.routing import route_points, route_queries
from gridtide.storage import Workspace


def imbalance(loads: DataFrame) -> DataFrame:
    """(rnd, min, mean, max, max over mean, coefficient of variation) of machine loads."""
    return loads.groupBy("rnd").agg(
        F.min("load").alias("min_load"), F.avg("load").alias("mean_load"), F.max("load").alias("max_load"),
        (F.max("load") / F.avg("load")).alias("max_over_mean"), (F.stddev_pop("load") / F.avg("load")).alias("variation"),
    )


def throttle(loads: DataFrame, capacity: float) -> DataFrame:
    """(rnd, accept): the share of arrivals that the slowest machine lets through."""
    return loads.groupBy("rnd").agg(F.least(F.lit(1.0), F.lit(capacity) / F.max("load")).alias("accept"))


def utilisation(loads: DataFrame, capacity: float, rounds: int = 5) -> DataFrame:
    """(period, min, mean, max) share of capacity used over periods of several rounds."""
    used = loads.withColumn("used", F.least(F.lit(1.0), F.col("load") / F.lit(capacity))).withColumn("period", F.floor(F.col("rnd") / rounds).cast("int"))
    by_machine = used.groupBy("period", "machine_id").agg(F.avg("used").alias("used"))
    return by_machine.groupBy("period").agg(F.min("used").alias("least"), F.avg("used").alias("mean"), F.max("used").alias("most"))


def units_of_work(rows: DataFrame) -> DataFrame:
    """(strategy, average and total units, mean latency, mean max over mean) over a run's rounds."""
    return rows.groupBy("strategy").agg(
        F.avg("units").alias("mean_units"), F.sum("units").alias("total_units"), F.avg("latency").alias("mean_latency"),
        F.avg(F.col("max_load") / F.nullif(F.col("mean_load"), F.lit(0.0))).alias("mean_imbalance"), F.sum("moved_queries").alias("moved_queries"),
    )


def ratios(summary: DataFrame, base: str = "history_grid") -> DataFrame:
    """Gain in units and latency quotient of each strategy against a baseline."""
    ref = summary.where(F.col("strategy") == base).select(F.col("mean_units").alias("b_units"), F.col("mean_latency").alias("b_latency"))
    return summary.join(F.broadcast(ref)).select("strategy", ((F.col("mean_units") - F.col("b_units")) / F.col("b_units")).alias("units_gain"), (F.col("b_latency") / F.col("mean_latency")).alias("latency_quotient"))


def stats_traffic(points: DataFrame, spec: GridSpec, sides: list[int], machines: list[int]) -> DataFrame:
    """Statistics sent in the collections of a stream, by grid side and machines: 2 a machine, against 5 a cell when counted centrally.

    ``collections`` are rounds with points, ``central`` counts all cells of each
    and ``touched`` only those with points of the round.
    """
    at = lambda value, low, extent, side: cell_of(F.col(value), low, extent, side)
    cells = [F.struct(F.lit(s).alias("side"), at("x", spec.x_lo, spec.width, s).alias("cx"), at("y", spec.y_lo, spec.height, s).alias("cy")) for s in sides]
    by_round = points.select("rnd", F.explode(F.array(*cells)).alias("c")).select("rnd", "c.*").distinct().groupBy("side", "rnd").agg(F.count("*").alias("cells"))
    by_side = by_round.groupBy("side").agg(F.count("*").alias("collections"), F.sum("cells").alias("cells"))
    full = by_side.withColumn("machines", F.explode(F.array(*map(F.lit, machines))))
    number = F.col("collections")
    return full.select(
        "side", "machines", "collections", (F.col("machines") * 2 * number).alias("decentral"), (F.col("side").cast("long") * F.col("side") * 5 * number).alias("central"), (F.col("cells") * 5).alias("touched")
    )


def counted_traffic(points: DataFrame, queries: DataFrame, machines: int) -> DataFrame:
    """(rnd, decentral, central): numbers sent by each round's end, 2 a machine against 5 for each cell that the round touched."""
    over = queries.withColumn("cx", F.explode(F.sequence("cx0", "cx1"))).withColumn("cy", F.explode(F.sequence("cy0", "cy1")))
    cells = points.select("rnd", "cx", "cy").unionByName(over.select("rnd", "cx", "cy")).distinct()
    return cells.groupBy("rnd").agg(F.lit(2 * machines).cast("long").alias("decentral"), (F.count("*") * 5).alias("central"))


def network_use(rows: DataFrame, forwarded: DataFrame, machines: int, share: float = 0.8) -> DataFrame:
    """(strategy, rnd, rows_sent, used): accepted points, new query copies, forwarded rows, moved queries and reports by round.

    ``used`` is against the reachable part (``share``) of a link that carries
    the busiest round of any strategy.  ``forwarded``: (strategy, rnd,
    forwarded).
    """
    sent = rows.join(forwarded, ["strategy", "rnd"], "left").fillna(0, ["forwarded", "moved_queries"])
    total = F.col("processed") + F.col("new_copies") + F.col("forwarded") + F.col("moved_queries") + F.lit(2 * machines)
    sent = sent.select("strategy", "rnd", total.alias("rows_sent"))
    most = sent.agg((F.max("rows_sent") / share).alias("link"))
    return sent.join(F.broadcast(most)).select("strategy", "rnd", "rows_sent", (F.col("rows_sent") / F.col("link")).alias("used"))


def network_rows(routed_points: DataFrame, routed_queries: DataFrame, machines: int) -> DataFrame:
    """Rows sent by round: routed points, routed query copies, reports."""
    p = routed_points.groupBy("rnd").agg(F.count("*").alias("points"))
    q = routed_queries.groupBy("rnd").agg(F.count("*").alias("query_copies"))
    return p.join(q, "rnd", "full").fillna(0).withColumn("reports", F.lit(2 * machines).cast("long"))


def update_counts(clipped: DataFrame, points: DataFrame) -> DataFrame:
    """Collector updates: two a point; rows plus columns a query and tile."""
    q = clipped.agg(F.sum((F.col("row1") - F.col("row0") + 1 + F.col("col1") - F.col("col0") + 1).cast("long")).alias("query_updates"), F.count("*").alias("query_copies"))
    return q.join(F.broadcast(points.agg((F.count("*") * 2).alias("point_updates"))))


def query_copies(routed: DataFrame, queries: DataFrame, machines: int) -> DataFrame:
    """Stored query copies: by tile routing, and when every machine holds every query."""
    tiled = routed.select("query_id", "machine_id").distinct().agg(F.count("*").alias("tiled"))
    return tiled.join(F.broadcast(queries.agg((F.count("*") * machines).alias("replicated"))))


def recovery_rounds(rows: DataFrame, onset: int, threshold: float) -> DataFrame:
    """(strategy, rounds): from a hotspot's onset until max over mean is back under a threshold; null if never."""
    late = rows.where((F.col("rnd") >= onset) & (F.col("max_load") <= F.col("mean_load") * threshold))
    first = late.groupBy("strategy").agg((F.min("rnd") - onset).alias("rounds"))
    return rows.select("strategy").distinct().join(first, "strategy", "left")


def cover_faults(plan: DataFrame, side: int) -> DataFrame:
    """Cells that lie in no tile or in several; empty for a sound plan."""
    from gridtide.operators.routing import cell_table

    spark = plan.sparkSession
    grid = spark.range(side * side).select((F.col("id") % side).cast("int").alias("cx"), F.floor(F.col("id") / side).cast("int").alias("cy"))
    held = cell_table(plan).groupBy("cx", "cy").agg(F.count("*").alias("tiles"))
    return grid.join(held, ["cx", "cy"], "left").fillna(0).where("tiles <> 1")


def match_faults(found: DataFrame, expected: DataFrame) -> DataFrame:
    """Lost, invented and repeated matches, as (kind, query_id, point_id)."""
    key = ["query_id", "point_id"]
    lost = expected.join(found, key, "left_anti").select(F.lit("lost").alias("kind"), *key)
    more = found.join(expected, key, "left_anti").select(F.lit("invented").alias("kind"), *key)
    again = found.groupBy(*key).agg(F.count("*").alias("n")).where("n > 1").select(F.lit("repeated").alias("kind"), *key)
    return lost.unionByName(more).unionByName(again)


def plan_faults(points: DataFrame, queries: DataFrame, plan: DataFrame, expected: DataFrame) -> DataFrame:
    """(kind, faults): as many as ``match_faults`` has between all matches under two plans, which are not listed.

    A plan treats all points of a cell and all queries of a rectangle of cells
    alike, so it is judged by cell and rectangle: how often the one's points
    meet the other's queries.  Only where that is faulty are the matches
    themselves counted, and those of ids that occur more than once.
    """
    space = Workspace(points.sparkSession, "faults")
    often = lambda rows, c: space.put(rows.groupBy(c).agg(F.count("*").alias("n")).where("n > 1").select(c), c)
    p_twice, q_twice = often(points, "point_id"), often(queries, "query_id")
    once_p, once_q = points.join(p_twice, "point_id", "left_anti"), queries.join(q_twice, "query_id", "left_anti")
    rects = ["cx0", "cy0", "cx1", "cy1"]
    key = ["cx", "cy", *rects]
    cells, boxes = once_p.select("cx", "cy").distinct(), once_q.select(*rects).distinct()

    def meetings(plan: DataFrame, name: str) -> DataFrame:
        over = route_queries(boxes, plan).withColumn("cx", F.explode(F.sequence("cx0", "cx1"))).withColumn("cy", F.explode(F.sequence("cy0", "cy1")))
        return route_points(cells, plan).drop("machine_id").join(over.drop("machine_id"), ["tile_id", "cx", "cy"]).groupBy(*key).agg(F.count("*").alias(name))

    both = meetings(plan, "found").join(meetings(expected, "due"), key, "full").fillna(0, ["found", "due"])
    kinds = both.withColumns({"lost": F.when(F.col("found") == 0, F.col("due")).otherwise(0), "invented": F.when(F.col("due") == 0, F.col("found")).otherwise(0), "repeated": (F.col("found") > 1).cast("long")})
    faulty = space.put(kinds.where("lost + invented + repeated > 0").select(*key, "lost", "invented", "repeated"), "faulty")
    hit = once_p.join(faulty, ["cx", "cy"]).join(once_q.drop("rnd", "tag"), rects).where("x BETWEEN x0 AND x1 AND y BETWEEN y0 AND y1 AND qts <= ts")
    names = ["lost", "invented", "repeated"]
    out = hit.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in names)).unpivot([], names, "kind", "faults")
    for some_p, some_q, ids in ((points.join(p_twice, "point_id", "left_semi"), queries, p_twice), (once_p, queries.join(q_twice, "query_id", "left_semi"), q_twice)):
        if not ids.isEmpty():
            listed = match_faults(match_continuous(some_p, some_q, plan), match_continuous(some_p, some_q, expected))
            out = out.unionByName(listed.groupBy("kind").agg(F.count("*").alias("faults")))
    return out.groupBy("kind").agg(F.sum("faults").alias("faults"))


def sliding_rate(points: DataFrame, rounds: int = 3) -> DataFrame:
    """(rnd, points, over the last ``rounds`` rounds)."""
    by_round = points.groupBy("rnd").agg(F.count("*").alias("points"))
    last = Window.partitionBy(F.lit(0)).orderBy("rnd").rangeBetween(-(rounds - 1), 0)
    return by_round.withColumn("recent", F.sum("points").over(last))
