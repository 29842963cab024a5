"""Matches counted without being listed, and matching by a machine's own index."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridtide.config import EVENTS
from gridtide.functions.grid import rectangle_cells, to_cells
from gridtide.operators import boxes, matching, measures
from gridtide.plans.layout import even_layout, plan_frame
from gridtide.streaming import loop


def crowd(spark, points=4000, queries=1500):
    """Points and queries around one place, many at the same time or with the same y, a few without a place."""
    p = spark.range(points).selectExpr("id AS point_id", "timestamp_ntz '2024-01-01' + make_dt_interval(0, 0, id % 700) AS ts", "int(id % 700 div 300) AS rnd", "IF(id % 97 = 0, NULL, double(id * 37 % 1600) / 50) AS x", "double(id * 11 % 40) AS y", "'click' AS tag")
    q = spark.range(queries).selectExpr("id AS query_id", "timestamp_ntz '2024-01-01' + make_dt_interval(0, 0, id * 7 % 720) AS qts", "0 AS rnd", "CAST(NULL AS string) AS tag", "double(id * 29 % 1600) / 50 AS x", "double(id * 13 % 40) AS y")
    q = q.selectExpr("*", "x - 4 AS x0", "x + 4 AS x1", "y - 1.5 AS y0", "y + 1.5 AS y1").drop("x", "y")
    return to_cells(p, EVENTS), rectangle_cells(q, EVENTS)


def pairs(points, queries):
    return points.alias("p").join(queries.alias("q"), F.expr("p.x BETWEEN q.x0 AND q.x1 AND p.y BETWEEN q.y0 AND q.y1 AND q.qts <= p.ts"))


def test_box_sums_equal_brute_force():
    rng = np.random.default_rng(3)
    for n, m in ((0, 3), (1, 5), (2, 9), (33, 20), (64, 40), (500, 200)):
        t, x, y = rng.integers(0, 60, n), rng.integers(0, 20, n) / 4, rng.integers(0, 9, n).astype(float)
        since, x0, y0 = rng.integers(-2, 63, m), rng.integers(-3, 20, m) / 4, rng.integers(-2, 9, m).astype(float)
        x1, y1 = x0 + rng.integers(-1, 9, m) / 4, y0 + rng.integers(-1, 5, m)
        count, total = boxes.box_sums((t, x, y), (since, x0, x1, y0, y1))
        hit = (t >= since[:, None]) & (x >= x0[:, None]) & (x <= x1[:, None]) & (y >= y0[:, None]) & (y <= y1[:, None])
        assert count.tolist() == hit.sum(1).tolist() and total == pytest.approx((hit * x).sum(1))


def test_aggregates_list_no_match(spark):
    points, queries = crowd(spark)
    got = matching.continuous_aggregate(points, queries, plan_frame(spark, even_layout(EVENTS, 8)), F.col("rnd"))
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plan and "HashJoin [cx" not in plan  # points never meet queries in a join
    want = pairs(points, queries).groupBy("q.query_id", "p.rnd").agg(F.count("*").alias("n"), F.sum("p.x").alias("s")).collect()
    held = {(r.query_id, r.win): (r.matched, r.total) for r in got.collect()}
    assert len(held) == len(want) > 0
    for r in want:
        assert held[r.query_id, r.rnd][0] == r.n and held[r.query_id, r.rnd][1] == pytest.approx(r.s, abs=1e-6)


def test_plan_faults_equal_those_of_listed_matches(spark, monkeypatch):
    points, queries = crowd(spark, 300, 120)
    points = points.unionByName(points.where("point_id IN (5, 6)"))  # delivered twice
    queries = queries.unionByName(queries.where("query_id = 7"))
    even = even_layout(EVENTS, 8)
    twice, gone = [*even, replace(even[0], tile_id=99)], even[1:]
    due = plan_frame(spark, even)
    for found, wanted in ((due, due), (plan_frame(spark, twice), due), (plan_frame(spark, gone), due), (due, plan_frame(spark, gone)), (due, plan_frame(spark, twice)), (plan_frame(spark, gone), plan_frame(spark, twice))):
        listed = measures.match_faults(matching.match_continuous(points, queries, found), matching.match_continuous(points, queries, wanted))
        want = {r.kind: r["count"] for r in listed.groupBy("kind").count().collect()}
        assert {r.kind: r.faults for r in measures.plan_faults(points, queries, found, wanted).collect() if r.faults} == want
    sides = []
    monkeypatch.setattr(measures, "match_continuous", lambda p, q, plan: sides.append(p) or matching.match_continuous(p, q, plan))
    one = points.dropDuplicates(["point_id"]), queries.dropDuplicates(["query_id"])
    assert measures.plan_faults(*one, due, due).agg(F.sum("faults")).first()[0] == 0 and not sides  # no match is listed


def test_tile_matches_meet_only_what_is_near(spark):
    points, queries = crowd(spark)
    plan = plan_frame(spark, even_layout(EVENTS, 8))
    got = matching.match_continuous(points, queries, plan, "tile")
    join = next(line for line in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join Inner" in line)
    assert "row#" in join and "col#" in join  # not every point of a tile with every query of it
    assert got.count() == got.distinct().count() == pairs(points, queries).count() > 0


def test_only_hot_keys_are_salted(spark):
    points, queries = crowd(spark, 3000, 900)
    one = spark.createDataFrame([(1, 1, 0), (2, 1, 0), (3, 9, 9)], "point_id long, row int, col int")
    crowded = one.unionByName(spark.range(100, 5000).selectExpr("id AS point_id", "7 AS row", "7 AS col"))
    asked = spark.createDataFrame([(k, 7, 7) for k in range(50)] + [(60, 1, 0), (61, 9, 9)], "query_id long, row int, col int")
    p, q = matching._salted(crowded, asked, ["row", "col"], 8)
    assert {(r.row, r["count"]) for r in q.groupBy("row").count().collect()} == {(7, 400), (1, 1), (9, 1)}  # the cold keys' queries are not copied
    assert p.count() == crowded.count() and p.where("row = 7").select("salt").distinct().count() == 8
    got = matching.match_continuous(points, queries, plan_frame(spark, even_layout(EVENTS, 8)), "tile", salts=8)
    assert got.count() == got.distinct().count() == pairs(points, queries).count()


def test_stream_aggregates_need_no_listed_match(spark, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    job = loop.BalancedStream(spark, str(tmp_path / "out"), listed=False)
    for k, some in enumerate((events.where("event_id % 2 = 0"), events.where("event_id % 2 = 1"))):
        job.batch(some, k)
    points, queries = loop.split_objects(events)
    number = "CASE WHEN {0} % 2 = 0 THEN 0 ELSE 1 END"
    seen = pairs(points, queries.withColumnRenamed("ts", "qts")).where(f"{number.format('q.query_id')} <= {number.format('p.point_id')}")
    want = {r.query_id: (r.n, r.s) for r in seen.groupBy("q.query_id").agg(F.count("*").alias("n"), F.sum("p.x").alias("s")).collect()}
    got = {r.query_id: (r.matched, r.total) for r in job.aggregates().collect()}
    assert got.keys() == want.keys() and want
    assert all(got[k][0] == n and got[k][1] == pytest.approx(s) for k, (n, s) in want.items())
    assert job.matches().isEmpty()


def test_stats_traffic_follows_the_stream(spark):
    points = spark.createDataFrame([(0, 1.0, 1.0), (0, 1.2, 1.0), (0, 200.0, 50.0), (2, 1.0, 1.0)], "rnd int, x double, y double")
    got = {(r.side, r.machines): (r.collections, r.decentral, r.central, r.touched) for r in measures.stats_traffic(points, EVENTS, [64, 1000], [8, 22]).collect()}
    assert got == {(64, 8): (2, 32, 40960, 15), (64, 22): (2, 88, 40960, 15), (1000, 8): (2, 32, 10_000_000, 20), (1000, 22): (2, 88, 10_000_000, 20)}


def test_stream_aggregates_do_not_read_listed_matches(spark, tmp_path, monkeypatch):
    """Matches are written and not shuffled again to be summed."""
    monkeypatch.setattr(loop.BalancedStream, "_match", lambda self, routed, live, batch_id: None)
    job = loop.BalancedStream(spark, str(tmp_path / "out"))
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    job.batch(events, 0)
    points, queries = loop.split_objects(events)
    assert job.aggregates().agg(F.sum("matched")).first()[0] == pairs(points, queries.withColumnRenamed("ts", "qts")).count() > 0


def test_stream_lists_matches_without_storing_them(spark, tmp_path):
    """What is stored grows with points and queries; a query that comes again counts from its first batch, one that comes late not before its own."""
    out = tmp_path / "out"
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    again = events.where("event_type = 'signup' AND event_id % 4 = 0")
    for k, some in enumerate((events.where("event_id % 2 = 0"), events.where("event_id % 2 = 1").unionByName(again))):
        loop.BalancedStream(spark, str(out), config=loop.BalanceConfig(policy="always")).batch(some, k)
    assert not (out / "matches").exists()
    points, queries = loop.split_objects(events)
    seen = pairs(points, queries.withColumnRenamed("ts", "qts")).where("q.query_id % 2 <= p.point_id % 2")
    want = sorted(tuple(r) for r in seen.select("q.query_id", "p.point_id").collect())
    held = loop.BalancedStream(spark, str(out)).matches()
    assert sorted(tuple(r) for r in held.select("query_id", "point_id").collect()) == want and want
    owners = {(r.point_id, r.tile_id, r.machine_id) for r in spark.read.parquet(f"{out}/points").collect()}
    assert {(r.point_id, r.tile_id, r.machine_id) for r in held.collect()} <= owners
