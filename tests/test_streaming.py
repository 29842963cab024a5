"""Streams: restart, late data, state."""

import duckdb
from pyspark.sql import functions as F

from gridtide.operators.governor import Governor
from gridtide.plans.layout import covers, plan_frame
from gridtide.config import EVENTS, BalanceConfig
from gridtide.operators import marginals, routing
from gridtide.streaming import loop

SF = "/root/testdata/sf0.001"


def parts(spark, folder, days):
    events = spark.read.parquet(f"{SF}/events.parquet")
    for i, (a, b) in enumerate(days):
        some = events.where((F.dayofyear("ts") > a) & (F.dayofyear("ts") <= b))
        some.coalesce(1).write.mode("append").parquet(f"{folder}")
    return events


def test_balanced_stream_survives_a_restart(spark, tmp_path):
    source, out = str(tmp_path / "in"), str(tmp_path / "out")
    events = parts(spark, source, [(0, 10), (10, 20)])
    config = BalanceConfig(policy="always")
    loop.BalancedStream(spark, out, config=config).start(loop.event_source(spark, source)).awaitTermination()
    parts(spark, source, [(20, 31)])
    job = loop.BalancedStream(spark, out, config=config)
    job.start(loop.event_source(spark, source)).awaitTermination()
    routed = spark.read.parquet(f"{out}/points/batch=*")
    assert routed.count() == routed.select("point_id").distinct().count() == events.where("event_type <> 'signup'").count()
    tiles = job.plans.read(3)
    assert covers(EVENTS, tiles) and len(tiles) > 8
    names = {"points": "point_id long, tile_id long, forwarded boolean", "matches": loop.MATCHES, "aggregates": loop.AGGREGATES, "marginals": loop.MARGINALS, "decisions": loop.DECISION, "moved": "query_id long, from_machine int, to_machine int, matched long, total double"}
    read = lambda: {n: sorted(map(str, job.table(n, s).collect())) for n, s in names.items()}
    before, plan = read(), job.plans.read(3)
    files = spark.read.parquet(source)
    third = files.where(F.dayofyear("ts") > 20)
    job.batch(third, 2)  # a replayed batch replaces what it wrote
    assert read() == before and job.plans.read(3) == plan
    assert before["moved"] and any("forwarded=True" in r for r in before["points"])
    # the marginals are those of all batches, counted anew under the last plan
    frame = plan_frame(spark, tiles)
    p, q = loop.split_objects(files)
    number = F.when(F.dayofyear("ts") <= 10, 0).when(F.dayofyear("ts") <= 20, 1).otherwise(2)
    got = marginals.collectors(*(f(route(x.withColumn("rnd", number), frame), frame) for f, route, x in ((marginals.in_tile, routing.route_points, p), (marginals.clip, routing.route_queries, q))))
    want = {(r.tile_id, r.axis, r.idx): (r.n, r.q, r.span_q) for r in marginals.fold(got, frame, 2, 0.5).collect()}
    held = {(r.tile_id, r.axis, r.idx): (r.n, r.q, r.span_q) for r in job.table("marginals", loop.MARGINALS).where("batch = 2").collect()}
    empty = {k for k, v in want.items() if k not in held}
    assert {k: v for k, v in want.items() if k in held} == held and all(want[k] == (0, 0, 0) for k in empty)


def test_governor_sees_both_kinds_and_survives_a_restart(spark, tmp_path):
    source, out = str(tmp_path / "in"), str(tmp_path / "out")
    days = [(k * 3, k * 3 + 3) for k in range(6)]
    for k, span in enumerate(days):
        parts(spark, source, [span])
        if k % 2:
            job = loop.BalancedStream(spark, out)  # lazy: the governor decides
            job.start(loop.event_source(spark, source)).awaitTermination()
    got = job.table("decisions", loop.DECISION).orderBy("batch").collect()
    copies = {r.batch: r["count"] for r in job.table("queries", loop.QUERIES).groupBy("batch").count().collect()}
    points = {r.batch: r["count"] for r in job.table("points", "point_id long").groupBy("batch").count().collect()}
    governor = Governor()
    assert [r.r_total for r in got] == [float(copies[k] + points[k]) for k in range(6)]
    assert [r.wanted for r in got] == [governor.step(r.r_total) for r in got]


def run_memory(spark, frame, name, mode="append"):
    q = frame.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def test_windows_sessions_and_duplicates(spark, tmp_path):
    source = str(tmp_path / "in")
    parts(spark, source, [(0, 15), (15, 31), (14, 15)])  # the third file repeats a day, late
    stream = lambda: loop.event_source(spark, source)
    daily = run_memory(spark, loop.windowed_arrivals(stream().where("event_id >= 0"), lateness="40 days"), "daily", "complete")
    con = duckdb.connect()
    total = con.execute(f"SELECT count(*) + sum(CAST(dayofyear(ts) = 15 AS INT)) FROM '{SF}/events.parquet'").fetchone()[0]
    assert daily.agg(F.sum("n")).first()[0] == total
    once = run_memory(spark, loop.deduplicated(stream(), "40 days").select("event_id"), "once")
    assert once.count() == 1000
    found = run_memory(spark, loop.sessions(stream(), lateness="1 hour"), "sess")
    assert found.count() > 0
    on, late = loop.late_split(spark.read.parquet(source), F.lit("2024-01-10").cast("timestamp_ntz"))
    assert on.count() + late.count() == spark.read.parquet(source).count() and late.count() > 0


def test_stream_join_equals_batch(spark, tmp_path):
    source = str(tmp_path / "in")
    parts(spark, source, [(0, 31)])
    points, _ = loop.split_objects(loop.event_source(spark, source))
    _, queries = loop.split_objects(loop.event_source(spark, source))
    got = run_memory(spark, loop.stream_matches(points, queries), "joined")
    p, q = loop.split_objects(spark.read.parquet(source))
    want = p.alias("p").join(q.alias("q"), F.expr("p.x between q.x0 and q.x1 and p.y between q.y0 and q.y1 and p.ts >= q.ts and p.ts <= q.ts + interval 2 days"))
    assert got.count() == want.count() > 0


def test_governor_as_state(spark, tmp_path):
    rows = [(i, float(r)) for i, r in enumerate([10, 9, 8, 7, 6, 9, 12, 3])]
    folder = str(tmp_path / "r")
    spark.createDataFrame(rows[:5], "rnd int, r_total double").coalesce(1).write.parquet(folder)
    spark.createDataFrame(rows[5:], "rnd int, r_total double").coalesce(1).write.mode("append").parquet(folder)
    key = "spark.sql.streaming.stateStore.providerClass"
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        source = spark.readStream.schema("rnd int, r_total double").option("maxFilesPerTrigger", 1).parquet(folder)
        got = {r.rnd: r.rebalance for r in run_memory(spark, loop.governed(source), "gov").collect()}
    finally:
        spark.conf.unset(key)
    g = Governor()
    assert got == {i: g.step(r) for i, r in rows}
