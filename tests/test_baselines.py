"""Baselines read the history that they are documented to read."""

from pyspark.sql import functions as F

from gridtide.config import GridSpec
from gridtide.operators import baselines
from gridtide.registry import QUERIES

DATA = "/root/testdata/sf0.001"


def test_replanning_reads_all_history(spark):
    spec, most = GridSpec(0.0, 0.0, 8.0, 8.0, 8), baselines.HISTORY_MOST
    # the oldest points, as many as the limited history holds, lie in one corner; the later ones in the other
    rows = spark.range(2 * most).withColumns({"late": (F.col("id") >= most).cast("int"), "k": F.col("id") % 4})
    at = lambda c: (F.col("late") * 6 + c).cast("int")
    points = rows.select(F.col("id").alias("point_id"), F.timestamp_seconds("id").alias("ts"), F.col("late").alias("rnd"), at(F.expr("k div 2")).alias("cx"), at(F.col("k") % 2).alias("cy"))
    queries = points.select(F.col("point_id").alias("query_id"), F.col("ts").alias("qts"), "rnd", F.col("cx").alias("cx0"), F.col("cy").alias("cy0"), F.col("cx").alias("cx1"), F.col("cy").alias("cy1"))
    (_, early), (_, whole) = baselines.halt_and_replan(spark, points, queries, spec, 4, [0, 1])
    corner = lambda tiles, low: sum(t.cx0 <= low + 1 and t.cx1 >= low and t.cy0 <= low + 1 and t.cy1 >= low for t in tiles)
    assert (corner(early, 0), corner(early, 6)) == (4, 1)
    assert corner(whole, 6) > 1
    assert baselines.history_layout(points, queries, spec, 4) == early  # the limited history stays limited


def test_control_plays_every_strategy_on_all_orders(spark):
    orders = spark.read.parquet(f"{DATA}/orders.parquet").count()
    rows = QUERIES["control_strategies"](spark, DATA).collect()
    units: dict[str, float] = {}
    for r in rows:
        units[r.strategy] = units.get(r.strategy, 0.0) + r.units
        assert r.live_queries == orders  # all orders are there from the first round on
    assert {"replicated", "uniform_grid", "history_grid", "adaptive_lazy_closed", "adaptive_always_closed"} == set(units)
    assert len(rows) == 30 * len(units)
    assert units["adaptive_lazy_closed"] >= units["uniform_grid"]  # balancing must not hurt where there is nothing to balance
