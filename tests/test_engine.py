"""Spark operators against DuckDB, the worked fixtures and each other."""

import duckdb
import pytest

import __spark_entry__ as entry_module
from gridtide import registry
from gridtide.config import EVENTS, BalanceConfig, GridSpec
from gridtide.operators import marginals, routing
from gridtide.operators import rounds as R
from gridtide.plans.layout import Tile, even_layout, plan_frame
from gridtide.plans.store import PlanStore
from gridtide.sources import tables

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for name in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{SF}/{name}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_sql(spark, duck, name, tmp_path):
    registry.queries()[name](spark, SF).write.parquet(str(tmp_path / "out"))
    duck.execute(f"CREATE OR REPLACE TEMP TABLE got AS SELECT * FROM '{tmp_path}/out/*.parquet'")
    duck.execute(f"CREATE OR REPLACE TEMP TABLE want AS {registry.oracle_sql()[name]}")
    shape = lambda t: sorted((r[0], r[1]) for r in duck.execute(f"DESCRIBE {t}").fetchall())
    assert [c for c, _ in shape("got")] == [c for c, _ in shape("want")]
    cols = ", ".join(f'"{c}"' for c, _ in shape("want"))
    for a, b in (("got", "want"), ("want", "got")):
        assert duck.execute(f"SELECT {cols} FROM {a} EXCEPT ALL SELECT {cols} FROM {b} LIMIT 3").fetchall() == []


def test_collectors_of_the_worked_tile(spark):
    """Two points in the third row, a query inside (row 1, col 0) and one from row 0 down to row 2 in col 1."""
    tile = [Tile(7, 0, 0, 0, 1, 3)]
    plan = plan_frame(spark, tile)
    points = spark.createDataFrame([(1, 0, 0, 2), (2, 0, 1, 2)], "point_id long, rnd int, cx int, cy int")
    queries = spark.createDataFrame([(1, 0, 0, 1, 0, 1), (2, 0, 1, 0, 1, 2)], "query_id long, rnd int, cx0 int, cy0 int, cx1 int, cy1 int")
    got = marginals.collectors(marginals.in_tile(routing.route_points(points, plan), plan), marginals.clip(routing.route_queries(queries, plan), plan))
    rows = {(r.axis, r.idx): (r.points, r.starts, r.spans) for r in got.collect()}
    assert rows == {("row", 0): (0, 1, 0), ("row", 1): (0, 1, 1), ("row", 2): (2, 0, 1), ("col", 0): (1, 1, 0), ("col", 1): (1, 1, 0)}


def test_fading_of_points(spark):
    plan = plan_frame(spark, [Tile(0, 0, 0, 0, 0, 0)])
    rows = [(r, 0, a, 0, n, 0, 0) for r, n in ((0, 8), (1, 4)) for a in ("row", "col")]
    got = spark.createDataFrame(rows, "rnd int, tile_id long, axis string, idx int, points long, starts long, spans long")
    assert [marginals.fold(got, plan, r, 0.5).first().n for r in range(3)] == [8.0, 8.0, 4.0]


def test_adaptive_beats_static_and_keeps_the_cover(spark):
    points, queries = tables.event_points(spark, SF), tables.event_queries(spark, SF)
    stream = R.counted(spark, points, queries, rounds=12)
    run = R.adaptive(spark, stream, EVENTS, BalanceConfig(policy="always", capacity=60.0))
    still = R.static_run(R.static_loads(stream, plan_frame(spark, even_layout(EVENTS, 8))), stream, "uniform", 8, BalanceConfig(machines=8, capacity=60.0))
    units = lambda r: sum(row["units"] for row in r.rows)
    assert units(run) > 1.5 * units(still)
    assert all(registry.layout.covers(EVENTS, tiles) for tiles in run.plans)
    assert {row["action"] for row in run.rows} & {"split", "subset"}


def test_plan_store_is_versioned_and_idempotent(spark, tmp_path):
    store = PlanStore(spark, str(tmp_path / "plans"))
    assert store.latest() is None
    tiles = even_layout(GridSpec(side=8), 4)
    store.publish(0, tiles)
    store.publish(3, tiles[:2])
    store.publish(3, tiles[1:])
    assert store.latest() == 3 and store.read(2) == sorted(tiles, key=lambda t: t.tile_id)
    assert store.read(5) == sorted(tiles[1:], key=lambda t: t.tile_id)


def test_point_store_prunes_and_replaces(spark, tmp_path):
    from pyspark.sql import functions as F

    from gridtide.plans.store import PointStore

    routed = routing.route_points(tables.event_points(spark, SF), plan_frame(spark, even_layout(EVENTS, 8)), "auto")
    store = PointStore(spark, str(tmp_path / "points"))
    store.append(routed.where(F.col("rnd") < 3))
    store.append(routed.where(F.col("rnd").between(2, 4)))
    assert store.read().count() == routed.where(F.col("rnd") <= 4).count()
    some = store.read(3, 3).where(F.col("tile_id") == routed.first().tile_id)
    assert "PartitionFilters: [isnotnull(rnd" in some._jdf.queryExecution().executedPlan().toString()


def test_large_plans_go_by_cell(spark, monkeypatch):
    monkeypatch.setattr(routing, "SMALL_PLAN", 4)
    monkeypatch.setattr(routing, "CELLS_MOST", 10)
    points, plan = tables.event_points(spark, SF), plan_frame(spark, even_layout(EVENTS, 8))
    pairs = lambda f: sorted(map(tuple, f.select("point_id", "tile_id").collect()))
    assert pairs(routing.route_points(points, plan, "auto")) == pairs(routing.route_points(points, plan))


def test_entry_and_names(spark):
    assert set(registry.oracle_sql()) <= set(registry.queries())
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())


def test_plans_reach_the_scan(spark):
    plan = tables.event_points(spark, SF).groupBy("cx").count()._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(event_type), Not(EqualTo(event_type,signup))]" in plan and "user_id" not in plan.split("ReadSchema", 1)[1]
    routed = routing.route_points(tables.event_points(spark, SF), plan_frame(spark, even_layout(EVENTS, 8)))
    text = routed._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" in text and "hashpartitioning" not in text
