"""Every query of the spatial engine, by name, with its SQL oracle.

Each query takes ``(spark, sf_dir)`` and works on whole tables.  The SQL states
the same result independently: by direct counts where the engine uses prefix
sums, by theta joins where it routes through tiles, by recursion where it folds.
"""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide import sql
from gridtide.config import EVENTS, MACHINES, BalanceConfig, GridSpec
from gridtide.operators import baselines, cost, euler, governor, marginals, matching, measures, planner, reports, routing, workloads
from gridtide.operators import rounds as R
from gridtide.plans import layout, lineage
from gridtide.plans.layout import Tile, even_layout, plan_frame, values_sql
from gridtide.sources import tables
from gridtide.storage import Workspace
from gridtide.streaming import loop

LAST = 29
SWITCH = 10
QUERIES: dict = {}
ORACLES: dict[str, str] = {}

LOC = """loc AS (
  SELECT event_id, ts, CAST(date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS rnd, user_id, event_type,
    value AS x, CAST(json_extract_string(props, '$.k') AS DOUBLE) AS y FROM events),
pts AS (
  SELECT event_id AS point_id, ts, rnd, x, y, event_type AS tag,
    CAST(greatest(0, least(63, floor(x * 64 / 256))) AS INTEGER) AS cx, CAST(greatest(0, least(63, floor(y * 64 / 100))) AS INTEGER) AS cy
  FROM loc WHERE event_type <> 'signup'),
qs AS (
  SELECT event_id AS query_id, ts AS qts, rnd, user_id AS subscriber_id, x - 4.0 AS x0, x + 4.0 AS x1, y - 1.5625 AS y0, y + 1.5625 AS y1,
    CAST(greatest(0, least(63, floor((x - 4.0) * 64 / 256))) AS INTEGER) AS cx0, CAST(greatest(0, least(63, floor((y - 1.5625) * 64 / 100))) AS INTEGER) AS cy0,
    CAST(greatest(0, least(63, floor((x + 4.0) * 64 / 256))) AS INTEGER) AS cx1, CAST(greatest(0, least(63, floor((y + 1.5625) * 64 / 100))) AS INTEGER) AS cy1
  FROM loc WHERE event_type = 'signup')"""
IN_TILE = "p.cx BETWEEN t.cx0 AND t.cx1 AND p.cy BETWEEN t.cy0 AND t.cy1"
OVER = "q.cx0 <= t.cx1 AND q.cx1 >= t.cx0 AND q.cy0 <= t.cy1 AND q.cy1 >= t.cy0"
EVEN = even_layout(EVENTS, MACHINES)


def spread_layout(tiles: int = 32) -> list[Tile]:
    """Several tiles a machine, dealt in turn."""
    return [Tile(t.tile_id, i % MACHINES, t.cx0, t.cy0, t.cx1, t.cy1) for i, t in enumerate(even_layout(EVENTS, tiles))]


SPREAD = spread_layout()


def stepped_layout() -> list[Tile]:
    """The even layout after one fixed split and one fixed move in round SWITCH."""
    tiles = layout.split_tile(EVEN, EVEN[0].tile_id, "row", 15, "second", 6, SWITCH)
    return layout.move_tiles(tiles, {EVEN[3].tile_id}, 7, SWITCH)


STEPPED = stepped_layout()
BASE = f"WITH RECURSIVE {values_sql(EVEN)}, {LOC}"
RP = f"rp AS (SELECT p.*, t.tile_id, t.machine_id, p.cy - t.cy0 AS tr, p.cx - t.cx0 AS tc FROM pts p JOIN plan t ON {IN_TILE})"
RQ = f"""rq AS (SELECT q.*, t.tile_id, t.machine_id, greatest(q.cy0, t.cy0) - t.cy0 AS row0, least(q.cy1, t.cy1) - t.cy0 AS row1,
  greatest(q.cx0, t.cx0) - t.cx0 AS col0, least(q.cx1, t.cx1) - t.cx0 AS col1 FROM qs q JOIN plan t ON {OVER})"""
SPINE = """spine AS (SELECT tile_id, 'row' AS axis, CAST(unnest(range(0, cy1 - cy0 + 1)) AS INTEGER) AS idx FROM plan
  UNION ALL SELECT tile_id, 'col', CAST(unnest(range(0, cx1 - cx0 + 1)) AS INTEGER) FROM plan)"""
PA = "pa AS (SELECT rnd, tile_id, 'row' AS axis, tr AS idx FROM rp UNION ALL SELECT rnd, tile_id, 'col', tc FROM rp)"
QA = "qa AS (SELECT rnd, tile_id, 'row' AS axis, row0 AS a, row1 AS b FROM rq UNION ALL SELECT rnd, tile_id, 'col', col0, col1 FROM rq)"


def query(name: str, text: str | None = None):
    def add(fn):
        QUERIES[name] = fn
        if text is not None:
            ORACLES[name] = text
        return fn

    return add


def queries() -> dict:
    """Query callables ``(spark, sf_dir) -> DataFrame`` by name."""
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    """DuckDB text for the queries that SQL can express."""
    return dict(ORACLES)


def _pq(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return tables.event_points(spark, sf_dir), tables.event_queries(spark, sf_dir)


def _plan(spark: SparkSession, tiles=EVEN) -> DataFrame:
    return plan_frame(spark, tiles)


def _collected(spark: SparkSession, sf_dir: str, tiles=EVEN) -> tuple[DataFrame, DataFrame]:
    p, q = _pq(spark, sf_dir)
    plan = _plan(spark, tiles)
    local = marginals.in_tile(routing.route_points(p, plan), plan)
    return marginals.collectors(local, marginals.clip(routing.route_queries(q, plan), plan)), plan


# ---- grid and routing

@query("cell_histogram", f"WITH {LOC} SELECT cx, cy, count(*) AS points FROM pts GROUP BY cx, cy")
def _(spark, sf_dir):
    return tables.event_points(spark, sf_dir).groupBy("cx", "cy").agg(F.count("*").alias("points"))


ROUTED = f"{BASE} SELECT p.point_id, t.tile_id, t.machine_id FROM pts p JOIN plan t ON {IN_TILE}"
for _method in ("probe", "lookup"):
    query(f"point_routing_{'even' if _method == 'probe' else _method}", ROUTED)(
        lambda spark, sf_dir, m=_method: routing.route_points(tables.event_points(spark, sf_dir), _plan(spark), m).select("point_id", "tile_id", "machine_id")
    )
ROUTED_Q = f"{BASE} SELECT q.query_id, t.tile_id, t.machine_id FROM qs q JOIN plan t ON {OVER}"
for _method in ("join", "hop", "cells"):
    query(f"query_routing_{_method}", ROUTED_Q)(
        lambda spark, sf_dir, m=_method: routing.route_queries(tables.event_queries(spark, sf_dir), _plan(spark), m, EVEN).select("query_id", "tile_id", "machine_id")
    )


def _big_queries(spark, sf_dir):
    return tables.event_queries(spark, sf_dir, side=40)


@query("hop_first_met_misses")
def _(spark, sf_dir):
    """Query-tile pairs that the walk from first-met cells leaves out, per layout; the repaired walk leaves out none."""
    q = _big_queries(spark, sf_dir)
    trap = [Tile(i, i, *b) for i, b in enumerate([(0, 0, 20, 31), (0, 32, 20, 63), (21, 0, 42, 63), (43, 0, 63, 31), (43, 32, 63, 63)])]
    out = []
    for name, tiles in (("even", EVEN), ("spread", SPREAD), ("trap", trap)):
        full = routing.route_queries(q, _plan(spark, tiles)).select("query_id", "tile_id")
        for entry in ("first_met", "clipped_corner"):
            got = routing.route_queries(q, _plan(spark, tiles), "hop", tiles, entry).select("query_id", "tile_id")
            missed = full.join(got, ["query_id", "tile_id"], "left_anti").agg(F.count("*").alias("missed"))
            out.append(missed.select(F.lit(name).alias("layout"), F.lit(entry).alias("entry"), "missed"))
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3]).unionByName(out[4]).unionByName(out[5])


@query("local_tile_lookup", f"{BASE}, {RP} SELECT point_id, tile_id, tr AS \"row\", tc AS col FROM rp")
def _(spark, sf_dir):
    routed = routing.route_points(tables.event_points(spark, sf_dir), _plan(spark))
    return routing.deliver(routed, _plan(spark)).select("point_id", "tile_id", (F.col("cy") - F.col("t_cy0")).alias("row"), (F.col("cx") - F.col("t_cx0")).alias("col"))


@query("machine_placement", f"{BASE}, {RP} SELECT machine_id, count(*) AS points, CAST(1 AS BIGINT) AS partitions FROM rp GROUP BY machine_id")
def _(spark, sf_dir):
    placed = routing.place(routing.route_points(tables.event_points(spark, sf_dir), _plan(spark)), MACHINES)
    return placed.withColumn("part", F.spark_partition_id()).groupBy("machine_id").agg(F.count("*").alias("points"), F.count_distinct("part").alias("partitions"))


@query("router_counts", f"WITH {LOC} SELECT CAST(point_id % 3 AS INTEGER) AS router, count(*) AS points FROM pts GROUP BY 1")
def _(spark, sf_dir):
    return routing.router_of(tables.event_points(spark, sf_dir), "point_id", 3).groupBy("router").agg(F.count("*").alias("points"))


TWO_PLANS = f"WITH {values_sql(EVEN, 'plan_a')}, {values_sql(STEPPED, 'plan_b')}, {LOC}, plans AS (SELECT 0 AS later, * FROM plan_a UNION ALL SELECT 1, * FROM plan_b)"


@query(
    "lagged_routing",
    f"""{TWO_PLANS} SELECT p.rnd, n.machine_id, count(*) AS points, CAST(sum(CASE WHEN o.machine_id <> n.machine_id THEN 1 ELSE 0 END) AS BIGINT) AS forwarded
    FROM pts p JOIN plans n ON n.later = CAST(p.rnd >= {SWITCH} AS INTEGER) AND p.cx BETWEEN n.cx0 AND n.cx1 AND p.cy BETWEEN n.cy0 AND n.cy1
    JOIN plans o ON o.later = CAST(greatest(0, p.rnd - 1) >= {SWITCH} AS INTEGER) AND p.cx BETWEEN o.cx0 AND o.cx1 AND p.cy BETWEEN o.cy0 AND o.cy1 GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    history = None
    for r in range(LAST + 1):
        one = plan_frame(spark, EVEN if r < SWITCH else STEPPED, r)
        history = one if history is None else history.unionByName(one)
    lagged = routing.route_with_lag(tables.event_points(spark, sf_dir), history)
    return lagged.groupBy("rnd", "machine_id").agg(F.count("*").alias("points"), F.sum(F.col("forwarded").cast("long")).alias("forwarded"))


# ---- statistics

@query("collectors_points", f"{BASE}, {RP}, {PA} SELECT rnd, tile_id, axis, idx, count(*) AS points FROM pa GROUP BY ALL")
def _(spark, sf_dir):
    plan = _plan(spark)
    return marginals.collect_points(marginals.in_tile(routing.route_points(tables.event_points(spark, sf_dir), plan), plan))


QCOLL = f"""{BASE}, {RQ}, {QA}, u AS (SELECT rnd, tile_id, axis, a AS idx, 1 AS s, 0 AS g FROM qa
  UNION ALL SELECT rnd, tile_id, axis, CAST(unnest(range(a + 1, b + 1)) AS INTEGER), 0, 1 FROM qa)
  SELECT rnd, tile_id, axis, idx, CAST(sum(s) AS BIGINT) AS starts, CAST(sum(g) AS BIGINT) AS spans FROM u GROUP BY ALL"""
for _method in ("explode", "delta"):

    def _collect(spark, sf_dir, m=_method):
        plan = _plan(spark)
        clipped = marginals.clip(routing.route_queries(tables.event_queries(spark, sf_dir), plan), plan)
        both = marginals.collect_query_starts(clipped).join(marginals.collect_query_spans(clipped, m), marginals.KEY, "full").fillna(0)
        return both.select(*marginals.KEY, F.col("starts").cast("long").alias("starts"), F.col("spans").cast("long").alias("spans"))

    query("collectors_queries" if _method == "explode" else "collectors_queries_delta", QCOLL)(_collect)


def _marginal_sql(at: int, decay: str) -> str:
    return f"""{BASE}, {RP}, {RQ}, {PA}, {QA}, {SPINE},
    pn AS (SELECT tile_id, axis, idx, sum({decay.format(at=at)}) AS n, sum(CAST(rnd = {at} AS INTEGER)) AS r FROM pa WHERE rnd <= {at} GROUP BY ALL),
    qn AS (SELECT tile_id, axis, a AS idx, count(*) AS q, sum(CAST(rnd = {at} AS INTEGER)) AS r FROM qa WHERE rnd <= {at} GROUP BY ALL),
    g AS (SELECT s.tile_id, s.axis, s.idx, count(*) AS span_q, sum(CAST(q.rnd = {at} AS INTEGER)) AS span_new FROM spine s
      JOIN qa q ON q.tile_id = s.tile_id AND q.axis = s.axis AND q.a < s.idx AND q.b >= s.idx AND q.rnd <= {at} GROUP BY ALL)
    SELECT s.tile_id, s.axis, s.idx, CAST(sum(coalesce(pn.n, 0)) OVER w AS DOUBLE) AS n, CAST(sum(coalesce(qn.q, 0)) OVER w AS BIGINT) AS q,
      CAST(sum(coalesce(pn.r, 0) + coalesce(qn.r, 0)) OVER w AS BIGINT) AS r, coalesce(g.span_q, 0) AS span_q, CAST(coalesce(g.span_new, 0) AS BIGINT) AS span_q_new
    FROM spine s LEFT JOIN pn USING (tile_id, axis, idx) LEFT JOIN qn USING (tile_id, axis, idx) LEFT JOIN g USING (tile_id, axis, idx)
    WINDOW w AS (PARTITION BY s.tile_id, s.axis ORDER BY s.idx)"""


for _name, _at, _decay, _method in (("marginals_fold", LAST, 1.0, "window"), ("marginals_naive", LAST, 1.0, "naive"), ("marginals_decay", 20, 0.5, "window")):

    def _fold(spark, sf_dir, at=_at, decay=_decay, m=_method):
        got, plan = _collected(spark, sf_dir)
        return marginals.fold(got, plan, at, decay, m)

    query(_name, _marginal_sql(_at, "1.0" if _decay == 1.0 else "pow(0.5, {at} - rnd)"))(_fold)


@query("marginals_stepwise", _marginal_sql(LAST, "pow(0.5, {at} - rnd)"))
def _(spark, sf_dir):
    """The same marginals, round after round from the ones before."""
    got, plan = _collected(spark, sf_dir)
    space = Workspace(spark, "stepwise")
    got, now = space.put(got, "collected", "rnd"), None
    for r in range(LAST + 1):
        now = space.put(marginals.fold_round(now, got.where(F.col("rnd") == r), plan, 0.5), f"round-{r}")
    return now.drop("fresh")


@query(
    "point_expiry",
    f"{BASE}, {RP} SELECT tile_id, count(*) AS n FROM rp WHERE rnd <= 20 AND rnd > 13 GROUP BY tile_id",
)
def _(spark, sf_dir):
    held = marginals.expire(tables.event_points(spark, sf_dir), 20, 7)
    return routing.route_points(held, _plan(spark)).groupBy("tile_id").agg(F.count("*").alias("n"))


STATS = f"""{RP}, {RQ}, st AS (SELECT t.tile_id, t.machine_id, coalesce(n, 0) AS n, coalesce(q, 0) AS q, coalesce(n, 0) + coalesce(q, 0) AS r
  FROM plan t LEFT JOIN (SELECT tile_id, count(*) AS n FROM rp GROUP BY 1) USING (tile_id) LEFT JOIN (SELECT tile_id, count(*) AS q FROM rq GROUP BY 1) USING (tile_id)),
  cs AS (SELECT *, CAST(n AS DOUBLE) * q * r AS numerator FROM st), mc AS (SELECT machine_id, sum(numerator) AS numerator, CAST(sum(r) AS BIGINT) AS r FROM cs GROUP BY 1)"""


def _one_round(spark, sf_dir, tiles=EVEN) -> DataFrame:
    """Tile stats of the whole stream as one round, without fading: (tile_id, machine_id, n, q, r, numerator)."""
    p, q = _pq(spark, sf_dir)
    plan = _plan(spark, tiles)
    points = routing.route_points(p, plan).groupBy("tile_id").agg(F.count("*").alias("n"))
    asked = routing.route_queries(q, plan).groupBy("tile_id").agg(F.count("*").alias("q"))
    full = plan.select("tile_id", "machine_id").join(points, "tile_id", "left").join(asked, "tile_id", "left").fillna(0, ["n", "q"])
    full = full.withColumn("r", F.col("n") + F.col("q"))
    return cost.tile_cost(full).withColumn("numerator", F.col("numerator").cast("double"))


@query("tile_totals", f"{BASE}, {STATS} SELECT tile_id, CAST(n AS DOUBLE) AS n, q, r FROM st")
def _(spark, sf_dir):
    got, plan = _collected(spark, sf_dir)
    flat = got.withColumn("rnd", F.lit(0))
    return marginals.tile_totals(marginals.fold(flat, plan, 0))


@query("tile_totals_by_column", f"{BASE}, {STATS} SELECT tile_id, CAST(n AS DOUBLE) AS n, q, r FROM st")
def _(spark, sf_dir):
    got, plan = _collected(spark, sf_dir)
    return marginals.tile_totals(marginals.fold(got.withColumn("rnd", F.lit(0)), plan, 0), "col")


SUBTILE = f"""{BASE}, {RP}, {RQ}, {PA}, {QA}, {SPINE},
  lines AS (SELECT tile_id, axis, idx FROM spine s WHERE EXISTS (SELECT 1 FROM spine o WHERE o.tile_id = s.tile_id AND o.axis = s.axis AND o.idx = s.idx + 1)),
  lp AS (SELECT l.tile_id, l.axis, l.idx, sum(CAST(p.idx <= l.idx AS INTEGER)) AS n1, sum(CAST(p.idx > l.idx AS INTEGER)) AS n2,
    sum(CAST(p.idx <= l.idx AND p.rnd = {LAST} AS INTEGER)) AS f1, sum(CAST(p.idx > l.idx AND p.rnd = {LAST} AS INTEGER)) AS f2 FROM lines l JOIN pa p USING (tile_id, axis) GROUP BY ALL),
  lq AS (SELECT l.tile_id, l.axis, l.idx, sum(CAST(q.a <= l.idx AS INTEGER)) AS q1, sum(CAST(q.b > l.idx AS INTEGER)) AS q2,
    sum(CAST(q.a <= l.idx AND q.rnd = {LAST} AS INTEGER)) AS f1, sum(CAST(q.b > l.idx AND q.rnd = {LAST} AS INTEGER)) AS f2 FROM lines l JOIN qa q USING (tile_id, axis) GROUP BY ALL)
  SELECT l.tile_id, l.axis, l.idx, CAST(coalesce(n1, 0) AS DOUBLE) AS n1, CAST(coalesce(q1, 0) AS BIGINT) AS q1, CAST(coalesce(lp.f1, 0) + coalesce(lq.f1, 0) AS BIGINT) AS r1,
    CAST(coalesce(n2, 0) AS DOUBLE) AS n2, CAST(coalesce(q2, 0) AS BIGINT) AS q2, CAST(coalesce(lp.f2, 0) + coalesce(lq.f2, 0) AS BIGINT) AS r2
  FROM lines l LEFT JOIN lp USING (tile_id, axis, idx) LEFT JOIN lq USING (tile_id, axis, idx)"""


@query("subtile_counts", SUBTILE)
def _(spark, sf_dir):
    got, plan = _collected(spark, sf_dir)
    return marginals.subtile_stats(marginals.fold(got, plan, LAST))


@query(
    "query_classes",
    f"""{BASE}, {RQ}, e AS (SELECT tile_id, row0, row1, CAST(unnest(range(row0, row1 + 1)) AS INTEGER) AS idx FROM rq)
    SELECT tile_id, idx, CAST(sum(CAST(idx = row0 AND idx < row1 AS INTEGER)) AS BIGINT) AS start_only, CAST(sum(CAST(idx > row0 AND idx = row1 AS INTEGER)) AS BIGINT) AS end_only,
      CAST(sum(CAST(row0 = row1 AS INTEGER)) AS BIGINT) AS both_ends, CAST(sum(CAST(idx > row0 AND idx < row1 AS INTEGER)) AS BIGINT) AS pass_through, count(*) AS total FROM e GROUP BY ALL""",
)
def _(spark, sf_dir):
    plan = _plan(spark)
    return marginals.classify_queries(marginals.clip(routing.route_queries(tables.event_queries(spark, sf_dir), plan), plan))


CHILDREN = [t for t in STEPPED if EVEN[0].tile_id in t.parent_ids]


@query("marginals_after_split", _marginal_sql(LAST, "1.0").replace(values_sql(EVEN), values_sql(CHILDREN)))
def _(spark, sf_dir):
    """Both parts of a split tile, recounted from the cells of that tile alone."""
    p, q = _pq(spark, sf_dir)
    return marginals.rebuild_marginals(p, q, _plan(spark, STEPPED), [t.tile_id for t in CHILDREN], LAST)


# ---- cost

@query("tile_cost", f"{BASE}, {STATS} SELECT tile_id, machine_id, n, q, r, numerator FROM cs")
def _(spark, sf_dir):
    return _one_round(spark, sf_dir)


@query("arrival_share", f"{BASE}, {STATS} SELECT tile_id, CAST(r AS DOUBLE) / (SELECT sum(r) FROM st) AS share FROM st")
def _(spark, sf_dir):
    return cost.arrival_share(_one_round(spark, sf_dir)).select("tile_id", "share")


@query("machine_report_rollup", f"{BASE.replace(values_sql(EVEN), values_sql(SPREAD))}, {STATS} SELECT machine_id, tile_id, sum(numerator) AS numerator, CAST(sum(r) AS BIGINT) AS r FROM cs GROUP BY ROLLUP (machine_id, tile_id)")
def _(spark, sf_dir):
    return cost.report_rollup(_one_round(spark, sf_dir, SPREAD))


SPREAD_BASE = BASE.replace(values_sql(EVEN), values_sql(SPREAD))


@query("machine_rank", f"{SPREAD_BASE}, {STATS} SELECT machine_id, numerator, r, CAST(row_number() OVER (ORDER BY numerator DESC, machine_id) AS INTEGER) AS place, numerator / (SELECT sum(r) FROM mc) AS cost FROM mc")
def _(spark, sf_dir):
    return cost.rank_machines(cost.machine_report(_one_round(spark, sf_dir, SPREAD)))


@query("donor_receiver", f"{SPREAD_BASE}, {STATS} SELECT (SELECT machine_id FROM mc ORDER BY numerator DESC, machine_id LIMIT 1) AS donor, (SELECT machine_id FROM mc ORDER BY numerator, machine_id LIMIT 1) AS receiver")
def _(spark, sf_dir):
    return planner.pick_pair(cost.machine_report(_one_round(spark, sf_dir, SPREAD)))


# ---- balancing

def _governor_sql(beta: int) -> str:
    return f"""{BASE}, {RP}, {RQ}, a AS (SELECT rnd, count(*) AS c FROM (SELECT rnd FROM rp UNION ALL SELECT rnd FROM rq) GROUP BY rnd),
    g(rnd, r_total, stage, rebalance, repeats) AS (
      SELECT rnd, CAST(c AS DOUBLE), 0, false, 1 FROM a WHERE rnd = (SELECT min(rnd) FROM a)
      UNION ALL
      SELECT rnd, c, CASE WHEN s <= -2 THEN 0 ELSE s END, CASE WHEN s <= -2 THEN NOT rebalance ELSE rebalance END, CASE WHEN s <= -2 THEN 1 ELSE repeats + 1 END
      FROM (SELECT a.rnd, CAST(a.c AS DOUBLE) AS c, g.rebalance, g.repeats,
              CASE WHEN g.repeats >= {beta} THEN -2 WHEN a.c > g.r_total THEN least(2, g.stage + 1) ELSE g.stage - 1 END AS s
            FROM g JOIN a ON a.rnd = g.rnd + 1))
    SELECT rnd, r_total, CAST(stage AS INTEGER) AS stage, rebalance, CAST(repeats AS INTEGER) AS repeats FROM g"""


def _arrivals(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    plan = _plan(spark)
    both = routing.route_points(p, plan).select("rnd").unionByName(routing.route_queries(q, plan).select("rnd"))
    return both.groupBy("rnd").agg(F.count("*").alias("r_total"))


for _name, _beta in (("governor_trace", 20), ("governor_forced_flip", 3)):
    query(_name, _governor_sql(_beta))(lambda spark, sf_dir, b=_beta: governor.govern(_arrivals(spark, sf_dir), b))

CAPS = "caps AS (SELECT machine_id, (numerator - (SELECT min(numerator) FROM mc)) / 2 AS cap FROM mc)"


def _greedy_sql(order: str) -> str:
    return f"""{SPREAD_BASE}, {STATS}, {CAPS}, o AS (SELECT machine_id, tile_id, numerator AS c, row_number() OVER (PARTITION BY machine_id ORDER BY {order}) AS k FROM cs),
    g(machine_id, k, tile_id, kept, total, done) AS (
      SELECT machine_id, CAST(0 AS BIGINT), CAST(-1 AS BIGINT), false, CAST(0 AS DOUBLE), false FROM caps
      UNION ALL
      SELECT machine_id, k, tile_id, fits, CASE WHEN fits THEN total + c ELSE total END, done OR (CASE WHEN fits THEN total + c ELSE total END) = cap
      FROM (SELECT o.machine_id, o.k, o.tile_id, o.c, g.total, g.done, caps.cap, NOT g.done AND g.total + o.c <= caps.cap AS fits
            FROM g JOIN o ON o.machine_id = g.machine_id AND o.k = g.k + 1 JOIN caps ON caps.machine_id = o.machine_id))
    SELECT machine_id, tile_id, kept FROM g WHERE k > 0"""


for _name, _order, _sql in (("greedy_subset", "cost", "numerator DESC, tile_id"), ("greedy_unsorted", "arrival", "tile_id")):

    def _greedy(spark, sf_dir, o=_order):
        stats = _one_round(spark, sf_dir, SPREAD)
        report = cost.machine_report(stats)
        low = report.agg(F.min("numerator").alias("low"))
        caps = report.join(F.broadcast(low)).select("machine_id", ((F.col("numerator") - F.col("low")) / 2).alias("cap"))
        return planner.greedy_frame(stats, caps, o)

    query(_name, _greedy_sql(_sql))(_greedy)


@query(
    "exact_subset",
    f"""{SPREAD_BASE}, {STATS}, {CAPS}, d AS (SELECT machine_id FROM mc ORDER BY numerator DESC, machine_id LIMIT 1),
    own AS (SELECT numerator AS c, row_number() OVER (ORDER BY tile_id) - 1 AS bit FROM cs WHERE machine_id = (SELECT machine_id FROM d)),
    masks AS (SELECT unnest(range(0, CAST(pow(2, (SELECT count(*) FROM own)) AS BIGINT))) AS mask),
    sums AS (SELECT mask, coalesce(sum(c), 0) AS total FROM masks LEFT JOIN own ON (mask >> bit) & 1 = 1 GROUP BY mask)
    SELECT max(total) AS best FROM sums WHERE total <= (SELECT cap FROM caps WHERE machine_id = (SELECT machine_id FROM d))""",
)
def _(spark, sf_dir):
    stats = _one_round(spark, sf_dir, SPREAD)
    report = cost.machine_report(stats).orderBy(F.desc("numerator"), "machine_id").collect()  # a row for each machine
    donor = report[0]
    cap = (donor["numerator"] - report[-1]["numerator"]) / 2
    return planner.exact_frame(stats.where(F.col("machine_id") == donor["machine_id"]), cap)


@query("subset_quality")
def _(spark, sf_dir):
    """Greedy and exact subset sums of every machine; the ratio is never under one half."""
    stats = _one_round(spark, sf_dir, SPREAD).collect()  # a row for each tile
    load: dict[int, float] = {}
    for r in stats:
        load[r["machine_id"]] = load.get(r["machine_id"], 0.0) + r["numerator"]
    low, rows = min(load.values()), []
    for m in sorted(load):
        own = [(r["tile_id"], r["numerator"]) for r in stats if r["machine_id"] == m]
        cap = (load[m] - low) / 2
        got, best = planner.greedy_subset(own, cap)[1], planner.exact_subset(own, cap)
        rows.append((m, cap, float(got), float(best), got / best if best else 1.0))
    return spark.createDataFrame(rows, "machine_id int, cap double, greedy double, exact double, ratio double")


LINES = SUBTILE.replace(f"p.rnd = {LAST}", "true").replace(f"q.rnd = {LAST}", "true").split("WITH RECURSIVE ", 1)[1]
SCAN = f"""WITH RECURSIVE sub AS (WITH RECURSIVE {LINES}), {values_sql(EVEN)}, {LOC}, {STATS},
  tot AS (SELECT cs.tile_id, cs.numerator AS cost, mc.numerator AS high, (SELECT min(numerator) FROM mc) AS low FROM cs JOIN mc USING (machine_id)),
  c AS (SELECT s.tile_id, s.axis, s.idx, n1 * q1 * r1 AS c1, n2 * q2 * r2 AS c2, cost, high, low FROM sub s JOIN tot USING (tile_id)),
  o AS (SELECT tile_id, axis, idx, 'first' AS moved, abs((high - cost + c2) - (low + c1)) AS gap FROM c UNION ALL SELECT tile_id, axis, idx, 'second', abs((high - cost + c1) - (low + c2)) FROM c),
  best AS (SELECT *, row_number() OVER (PARTITION BY tile_id ORDER BY gap, axis <> 'row', moved, idx) AS k FROM o)"""
SPLITS = f"{SCAN} SELECT tile_id, axis, idx, moved, gap FROM best WHERE k = 1"


def _folded(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """(marginals, tile stats) of the whole stream as one round under the even layout: the stream is read and routed once."""
    got, plan = _collected(spark, sf_dir)
    rows = Workspace(spark, "folded").put(marginals.fold(got.withColumn("rnd", F.lit(0)), plan, 0), "rows")
    stats = marginals.tile_totals(rows).join(plan.select("tile_id", "machine_id"), "tile_id")
    return rows, stats.withColumn("numerator", F.col("n") * F.col("q") * F.col("r"))


def _split_inputs(spark, sf_dir):
    rows, stats = _folded(spark, sf_dir)
    report = cost.machine_report(stats)
    low = report.agg(F.min("numerator").alias("low"))
    totals = stats.select("tile_id", "machine_id", F.col("numerator").alias("cost")).join(report.select("machine_id", F.col("numerator").alias("high")), "machine_id").join(F.broadcast(low)).drop("machine_id")
    return rows, totals


@query("split_scan", SPLITS)
def _(spark, sf_dir):
    return planner.best_of_scan(planner.split_scan(*_split_inputs(spark, sf_dir)))


@query("split_binary", SPLITS)
def _(spark, sf_dir):
    """The best cut of every tile by binary search, each tile in a task of its own."""
    rows, totals = _split_inputs(spark, sf_dir)

    def search(frame: pd.DataFrame) -> pd.DataFrame:
        axes = planner.axis_stats(frame.to_dict("records"))
        one = frame.iloc[0]
        cut = planner.best_split(axes, one["cost"], one["high"], one["low"])
        return pd.DataFrame([(one["tile_id"], cut.axis, cut.after, cut.moved, cut.gap)], columns=["tile_id", "axis", "idx", "moved", "gap"])

    return rows.join(F.broadcast(totals), "tile_id").groupBy("tile_id").applyInPandas(search, "tile_id long, axis string, idx int, moved string, gap double")


STEP = f"""{SCAN}, d AS (SELECT machine_id, numerator FROM mc ORDER BY numerator DESC, machine_id LIMIT 1), e AS (SELECT machine_id, numerator FROM mc ORDER BY numerator, machine_id LIMIT 1),
    fit AS (SELECT count(*) AS k FROM cs WHERE machine_id = (SELECT machine_id FROM d) AND numerator > 0 AND numerator <= ((SELECT numerator FROM d) - (SELECT numerator FROM e)) / 2),
    top AS (SELECT tile_id FROM cs WHERE machine_id = (SELECT machine_id FROM d) ORDER BY numerator DESC, tile_id LIMIT 1),
    step AS (SELECT CASE WHEN fit.k > 0 THEN 'subset' ELSE 'split' END AS kind, d.machine_id AS donor, e.machine_id AS receiver, b.tile_id, b.axis, b.idx, b.moved, b.gap
      FROM d, e, fit, best b WHERE b.k = 1 AND b.tile_id = (SELECT tile_id FROM top))"""


def _first_step(spark, sf_dir, at_round: int = 1):
    """(tiles, action) of one rebalance of the even layout, the whole stream taken as one round."""
    rows, stats = _folded(spark, sf_dir)
    report = {r["machine_id"]: r["numerator"] for r in cost.machine_report(stats).collect()}
    costs = lambda m: {r["tile_id"]: r["numerator"] for r in stats.where(F.col("machine_id") == m).collect()}
    axes = lambda t: planner.axis_stats(rows.where(F.col("tile_id") == t.tile_id).collect())
    return planner.rebalance_once(EVEN, report, costs, axes, at_round)


@query("rebalance_first_step", f"{STEP} SELECT * FROM step")
def _(spark, sf_dir):
    _, act = _first_step(spark, sf_dir)
    cut = act.cut or planner.Cut(0.0, None, None, None)
    return spark.createDataFrame([(act.kind, act.donor, act.receiver, act.tiles[0], cut.axis, cut.after, cut.moved, cut.gap)], "kind string, donor int, receiver int, tile_id long, axis string, idx int, moved string, gap double")


OWNED = f"owned AS (SELECT t.* REPLACE (CAST(coalesce(c.n, 0) % 2 AS INTEGER) AS machine_id) FROM plan t LEFT JOIN (SELECT tile_id, count(*) AS n FROM rp GROUP BY 1) c USING (tile_id))"


@query(
    "merge_once",
    f"""{SPREAD_BASE}, {RP}, {OWNED}, pairs AS (SELECT a.tile_id AS a, b.tile_id AS b, a.machine_id, least(a.cx0, b.cx0) AS cx0, least(a.cy0, b.cy0) AS cy0, greatest(a.cx1, b.cx1) AS cx1, greatest(a.cy1, b.cy1) AS cy1
      FROM owned a JOIN owned b ON a.tile_id < b.tile_id AND a.machine_id = b.machine_id AND (
        (a.cy0 = b.cy0 AND a.cy1 = b.cy1 AND (a.cx1 + 1 = b.cx0 OR b.cx1 + 1 = a.cx0)) OR (a.cx0 = b.cx0 AND a.cx1 = b.cx1 AND (a.cy1 + 1 = b.cy0 OR b.cy1 + 1 = a.cy0))) ORDER BY 1, 2 LIMIT 1)
    SELECT tile_id, machine_id, cx0, cy0, cx1, cy1 FROM owned WHERE tile_id NOT IN (SELECT a FROM pairs UNION SELECT b FROM pairs)
    UNION ALL SELECT (SELECT max(tile_id) + 1 FROM owned), machine_id, cx0, cy0, cx1, cy1 FROM pairs""",
)
def _(spark, sf_dir):
    """One merge among tiles whose owners the stream decides (even and odd numbers of points)."""
    counts = routing.route_points(tables.event_points(spark, sf_dir), _plan(spark, SPREAD)).groupBy("tile_id").count().collect()  # a row for each tile
    held = {r["tile_id"]: r["count"] for r in counts}
    owned = [Tile(t.tile_id, held.get(t.tile_id, 0) % 2, t.cx0, t.cy0, t.cx1, t.cy1) for t in SPREAD]
    return plan_frame(spark, layout.merge_once(owned)).select("tile_id", "machine_id", "cx0", "cy0", "cx1", "cy1")


# ---- rounds and strategies

def _capacity(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    stream = R.counted(spark, p, q)
    history = baselines.history_layout(p, q, EVENTS, MACHINES, max(200, p.count() // 4))
    return stream, history, baselines.default_capacity(stream, history, MACHINES)


def _adaptive(spark, sf_dir, **settings):
    stream, _, capacity = _capacity(spark, sf_dir)
    return R.adaptive(spark, stream, EVENTS, BalanceConfig(machines=MACHINES, capacity=capacity, **settings))


@query("adaptive_rounds")
def _(spark, sf_dir):
    """All rounds of the event stream with lazy, closed-loop balancing."""
    return R.run_frame(spark, _adaptive(spark, sf_dir))


@query("adaptive_policies")
def _(spark, sf_dir):
    """Lazy, always and never rebalancing, and the open loop, summed up."""
    stream, _, capacity = _capacity(spark, sf_dir)
    play = lambda **k: (stream, BalanceConfig(machines=MACHINES, capacity=capacity, **k), None)
    runs = R.adaptive_all(spark, EVENTS, [play(), play(loop="open"), play(policy="always"), play(policy="never")])
    return measures.units_of_work(R.run_frame(spark, *runs))


@query("adaptive_plan_history")
def _(spark, sf_dir):
    """Every tile that balancing made, with its lineage."""
    run = _adaptive(spark, sf_dir, policy="always", merge_every=10)
    rows = lineage.tile_history([EVEN, *run.plans])
    return plan_frame(spark, rows).drop("round")


def _strategies(spark, sf_dir, name):
    p, q = _pq(spark, sf_dir)
    _, history, capacity = _capacity(spark, sf_dir)
    wp, wq = workloads.workload(spark, p, q, EVENTS, name)
    config = BalanceConfig(machines=MACHINES, capacity=capacity)
    return R.run_frame(spark, *baselines.compare(spark, R.counted(spark, wp, wq), history, EVENTS, config))


for _name in workloads.SHAPES:
    query(f"strategies_{_name}")(lambda spark, sf_dir, n=_name: measures.units_of_work(_strategies(spark, sf_dir, n)))


def _other(spark, sf_dir, points, queries, spec=EVENTS):
    stream = R.counted(spark, points, queries)
    history = baselines.history_layout(points, queries, spec, MACHINES, max(200, points.count() // 4))
    config = BalanceConfig(machines=MACHINES, capacity=baselines.default_capacity(stream, history, MACHINES))
    return measures.units_of_work(R.run_frame(spark, *baselines.compare(spark, stream, history, spec, config, ("lazy", "always"))))


@query("strategies_drift")
def _(spark, sf_dir):
    """All strategies while the whole stream wanders to the right, a cell a round."""
    p, q = _pq(spark, sf_dir)
    return _other(spark, sf_dir, workloads.drift(p, EVENTS), q)


@query("strategies_replay")
def _(spark, sf_dir):
    """All strategies on the stream played three times; queries come with the first pass."""
    p, q = _pq(spark, sf_dir)
    return _other(spark, sf_dir, tables.replay(p, 3), q)


@query("strategies_embeddings")
def _(spark, sf_dir):
    """All strategies on the natural blob of the embeddings; every tenth vector also asks for its surroundings."""
    p = tables.embedding_points(spark, sf_dir).withColumn("rnd", F.expr("int(point_id div 50)")).withColumn("ts", F.col("point_id"))
    q = tables.embedding_queries(spark, sf_dir)
    return _other(spark, sf_dir, p, q, GridSpec(-0.5, -0.5, 1.0, 1.0, 64))


@query("strategy_ratios")
def _(spark, sf_dir):
    """Gain in units of work and latency quotient against the history grid, plain stream."""
    return measures.ratios(measures.units_of_work(_strategies(spark, sf_dir, "plain")))


@query("utilisation_hotspot")
def _(spark, sf_dir):
    """Least, mean and most capacity used by period of five rounds while a hotspot comes and goes."""
    _, _, capacity = _capacity(spark, sf_dir)
    rows = _strategies(spark, sf_dir, "hotspot_uniform").withColumn("period", F.floor(F.col("rnd") / 5).cast("int"))
    used = lambda c: F.avg(F.least(F.lit(1.0), F.col(c) / F.lit(capacity)))
    return rows.groupBy("strategy", "period").agg(used("min_load").alias("least"), used("mean_load").alias("mean"), used("max_load").alias("most"))


@query("network_hotspot")
def _(spark, sf_dir):
    """Least, mean and most of the network used by period of five rounds while a hotspot comes and goes."""
    p, q = _pq(spark, sf_dir)
    _, history, capacity = _capacity(spark, sf_dir)
    wp, wq = workloads.workload(spark, p, q, EVENTS, "hotspot_uniform")
    stream = R.counted(spark, wp, wq)
    config = BalanceConfig(machines=MACHINES, capacity=capacity)
    runs = baselines.static_runs(spark, stream, history, EVENTS, config) + [R.adaptive(spark, stream, EVENTS, config)]
    plans = {"uniform_grid": [EVEN], "history_grid": [history], runs[-1].rows[0]["strategy"]: [EVEN, *runs[-1].plans]}
    copies = forwarded = None
    for name, tiles in plans.items():
        by_round = None
        for r in range(stream.rounds):
            one = plan_frame(spark, tiles[min(r, len(tiles) - 1)], r)
            by_round = one if by_round is None else by_round.unionByName(one)
        routed = routing.route_queries_by_round(wq, by_round).groupBy("rnd").agg(F.count("*").alias("new_copies"))
        sent = routing.route_with_lag(wp, by_round).groupBy("rnd").agg(F.sum(F.col("forwarded").cast("long")).alias("forwarded"))
        tag = lambda f: f.withColumn("strategy", F.lit(name))  # noqa: B023, E731
        copies, forwarded = (tag(routed), tag(sent)) if copies is None else (copies.unionByName(tag(routed)), forwarded.unionByName(tag(sent)))
    all_of = wq.groupBy("rnd").agg((F.count("*") * MACHINES).alias("new_copies")).withColumn("strategy", F.lit("replicated"))
    rows = R.run_frame(spark, *runs).join(copies.unionByName(all_of), ["strategy", "rnd"], "left").fillna(0, ["new_copies"])
    used = measures.network_use(rows, forwarded, MACHINES).withColumn("period", F.floor(F.col("rnd") / 5).cast("int"))
    return used.groupBy("strategy", "period").agg(F.min("used").alias("least"), F.avg("used").alias("mean"), F.max("used").alias("most"), F.sum("rows_sent").alias("rows_sent"))


@query("hotspot_recovery")
def _(spark, sf_dir):
    """Rounds from a hotspot's onset until max over mean is back under 2.5."""
    return measures.recovery_rounds(_strategies(spark, sf_dir, "hotspot_step"), 10, 2.5)


LOADS = f"""{BASE}, {RP}, {RQ}, rounds AS (SELECT CAST(unnest(range(0, 30)) AS INTEGER) AS rnd),
  lp AS (SELECT rnd, tile_id, count(*) AS fresh FROM rp GROUP BY 1, 2),
  lq AS (SELECT r.rnd, q.tile_id, count(*) AS live FROM rounds r JOIN rq q ON q.rnd <= r.rnd GROUP BY 1, 2),
  loads AS (SELECT r.rnd, t.machine_id, CAST(sum(coalesce(fresh, 0) * coalesce(live, 0)) AS BIGINT) AS load, CAST(sum(coalesce(fresh, 0)) AS BIGINT) AS fresh
    FROM rounds r CROSS JOIN plan t LEFT JOIN lp ON lp.rnd = r.rnd AND lp.tile_id = t.tile_id LEFT JOIN lq ON lq.rnd = r.rnd AND lq.tile_id = t.tile_id GROUP BY 1, 2)"""


FACTORS = (1, 2, 4, 8, 16)
FINE, REPLICAS = GridSpec(side=256), 11  # replicas have the routers' machines too: 30 to 22 as published
HELD_FACTOR = 8  # a machine can hold so many times the base queries, so replicas overflow at the largest factor


@query("query_scaling")
def _(spark, sf_dir):
    """Units of work, latency and queries held by strategy and query count.

    All queries are there before the first round; executors search an index;
    capacity is the same at every factor; all adaptive runs play together.
    ``settled_`` figures are of the last ten rounds, after the cold start.
    """
    p, q = tables.event_points(spark, sf_dir, FINE), tables.event_queries(spark, sf_dir, FINE, side=1)
    n = q.count()
    history = baselines.history_layout(p, q, FINE, MACHINES, max(200, p.count() // 4))
    streams = {k: R.counted(spark, p, workloads.scale_queries(q, k, FINE, -1), indexed=True) for k in FACTORS}
    capacity = baselines.default_capacity(streams[1], history, MACHINES, "index")
    config = BalanceConfig(machines=MACHINES, capacity=capacity, executor="index", memory=HELD_FACTOR * n, policy="always")
    runs = R.adaptive_all(spark, FINE, [(s, config, None) for s in streams.values()])
    out = None
    for (k, stream), run in zip(streams.items(), runs, strict=True):
        rows = R.run_frame(spark, *baselines.static_runs(spark, stream, history, FINE, config, REPLICAS), run)
        held = rows.groupBy("strategy").agg(F.max("held").alias("most_held"), (F.max("held") > config.memory).alias("failed"))
        settled = rows.where(F.col("rnd") >= LAST - 9).groupBy("strategy").agg(F.avg("units").alias("settled_units"), F.avg("latency").alias("settled_latency"))
        rows = measures.units_of_work(rows).join(held, "strategy").join(settled, "strategy").withColumn("factor", F.lit(k)).withColumn("queries", F.lit(n * k).cast("long"))
        out = rows if out is None else out.unionByName(rows)
    return out


def _scaled_sql() -> str:
    shift = lambda salt: f"CASE WHEN copy = 0 THEN 0 ELSE CAST('0x' || substr(md5(CAST(query_id * f + copy AS VARCHAR) || ':{salt}'), 1, 7) AS BIGINT) % 5 - 2 END"
    move = lambda c, s: f"greatest(0, least(63, {c} + {shift(s)}))"
    return f"""s AS (SELECT f, copy, {', '.join(f"{move(c, c[1])} AS {c}" for c in R.RECT)} FROM qs CROSS JOIN (SELECT f, unnest(range(0, f)) AS copy FROM (SELECT unnest([{', '.join(map(str, FACTORS))}]) AS f)))"""


@query(
    "static_scaling",
    f"""{BASE}, {_scaled_sql()}, {RP}, lp AS (SELECT rnd, tile_id, machine_id, count(*) AS fresh FROM rp GROUP BY ALL), lq AS (SELECT f, t.tile_id, count(*) AS held FROM s q JOIN plan t ON {OVER} GROUP BY ALL),
    rounds AS (SELECT CAST(unnest(range(0, 30)) AS INTEGER) AS rnd), n AS (SELECT f, count(*) AS live FROM s GROUP BY f), a AS (SELECT rnd, count(*) AS arrivals FROM pts GROUP BY rnd),
    tiled AS (SELECT 'uniform_grid' AS strategy, n.f, r.rnd, t.machine_id, sum(coalesce(fresh, 0) * coalesce(held, 0)) AS load FROM n CROSS JOIN rounds r CROSS JOIN plan t
      LEFT JOIN lp ON lp.rnd = r.rnd AND lp.tile_id = t.tile_id LEFT JOIN lq ON lq.f = n.f AND lq.tile_id = t.tile_id GROUP BY ALL),
    dealt AS (SELECT 'replicated' AS strategy, n.f, r.rnd, t.machine_id, (coalesce(arrivals, 0) // {MACHINES} + CASE WHEN t.machine_id < coalesce(arrivals, 0) % {MACHINES} THEN 1 ELSE 0 END) * live AS load
      FROM n CROSS JOIN rounds r CROSS JOIN plan t LEFT JOIN a ON a.rnd = r.rnd),
    m AS (SELECT strategy, f, rnd, CAST(max(load) AS DOUBLE) AS max_load, CAST(sum(load) AS DOUBLE) / {MACHINES} AS mean_load, CASE WHEN sum(load) = 0 THEN 0.0 ELSE CAST(sum(load * load) AS DOUBLE) / CAST(sum(load) AS DOUBLE) END AS latency
      FROM (SELECT * FROM tiled UNION ALL SELECT * FROM dealt) GROUP BY ALL)
    SELECT CAST(f AS INTEGER) AS factor, strategy, m.rnd, max_load, mean_load, latency, live * (CASE WHEN max_load = 0 THEN 1.0::DOUBLE ELSE least(1.0::DOUBLE, CAST(20000 AS DOUBLE) / max_load) END) * coalesce(arrivals, 0) AS units
    FROM m JOIN n USING (f) LEFT JOIN a ON a.rnd = m.rnd""",
)
def _(spark, sf_dir):
    """Rounds of the replicated and the uniform strategy at every number of preloaded queries, with scanning executors."""
    p, q = _pq(spark, sf_dir)
    config, out = BalanceConfig(machines=MACHINES, capacity=20000.0), None
    for k in FACTORS:
        stream = R.counted(spark, p, workloads.scale_queries(q, k, EVENTS, -1), 30)
        rows = R.run_frame(spark, *baselines.static_runs(spark, stream, EVEN, EVENTS, config)[:2]).select(F.lit(k).alias("factor"), "strategy", "rnd", "max_load", "mean_load", "latency", "units")
        out = rows if out is None else out.unionByName(rows)
    return out


@query(
    "static_rounds",
    f"""{LOADS}, d AS (SELECT rnd, machine_id, (sum(fresh) OVER r // {MACHINES} + CASE WHEN machine_id < sum(fresh) OVER r % {MACHINES} THEN 1 ELSE 0 END) * (SELECT count(*) FROM qs WHERE qs.rnd <= loads.rnd) AS load, sum(fresh) OVER r AS arrivals FROM loads WINDOW r AS (PARTITION BY rnd)),
    u AS (SELECT 'uniform_grid' AS strategy, rnd, load, sum(fresh) OVER (PARTITION BY rnd) AS arrivals FROM loads UNION ALL SELECT 'replicated', rnd, load, arrivals FROM d),
    m AS (SELECT strategy, rnd, arrivals, CAST(max(load) AS DOUBLE) AS max_load, CAST(min(load) AS DOUBLE) AS min_load, CAST(sum(load) AS DOUBLE) / {MACHINES} AS mean_load, CASE WHEN sum(load) = 0 THEN 0.0 ELSE CAST(sum(load * load) AS DOUBLE) / CAST(sum(load) AS DOUBLE) END AS latency,
      CASE WHEN max(load) = 0 THEN 1.0::DOUBLE ELSE least(1.0::DOUBLE, CAST(20000 AS DOUBLE) / max(load)) END AS accept, (SELECT count(*) FROM qs WHERE qs.rnd <= any_value(w.rnd)) AS live FROM u w GROUP BY strategy, rnd, arrivals)
    SELECT strategy, rnd, max_load, min_load, mean_load, latency, accept, live * accept * arrivals AS units FROM m""",
)
def _(spark, sf_dir):
    """Every round of the replicated and the uniform strategy."""
    stream = R.counted(spark, *_pq(spark, sf_dir), 30)
    runs = baselines.static_runs(spark, stream, EVEN, EVENTS, BalanceConfig(machines=MACHINES, capacity=20000.0))[:2]
    return R.run_frame(spark, *runs).select("strategy", "rnd", "max_load", "min_load", "mean_load", "latency", "accept", "units")


@query("history_layout")
def _(spark, sf_dir):
    """The history grid and its cost for each machine on that history."""
    p, q = _pq(spark, sf_dir)
    most = max(200, p.count() // 4)
    tiles = baselines.history_layout(p, q, EVENTS, MACHINES, most)
    held = baselines.layout_costs(p.orderBy("ts", "point_id").limit(most), q.orderBy("qts", "query_id").limit(most // 2), tiles)
    return plan_frame(spark, tiles).select("tile_id", "machine_id", "cx0", "cy0", "cx1", "cy1").join(held, "machine_id", "left").fillna(0.0)


@query("halt_and_replan")
def _(spark, sf_dir):
    """Centralised repartitioning at the end of every round: the plans."""
    p, q = _pq(spark, sf_dir)
    rows = [(r, t.machine_id, t.cx0, t.cy0, t.cx1, t.cy1) for r, tiles in baselines.halt_and_replan(spark, p, q, EVENTS, MACHINES) for t in tiles]
    return spark.createDataFrame(rows, "rnd int, machine_id int, cx0 int, cy0 int, cx1 int, cy1 int")


@query("round_overheads")
def _(spark, sf_dir):
    """Measured seconds of each step of a round, and rows that reach the driver."""
    stream, _, _ = _capacity(spark, sf_dir)
    plan, rows = _plan(spark), []

    def timed(step, work):
        start = time.perf_counter()
        n = work()
        rows.append((step, time.perf_counter() - start, int(n)))

    p, q = _pq(spark, sf_dir)
    timed("route_points", lambda: routing.route_points(p, plan).count())
    timed("route_queries", lambda: routing.route_queries(q, plan).count())
    timed("collect_and_fold", lambda: marginals.fold(_collected(spark, sf_dir)[0], plan, LAST, 0.5).count())
    space = Workspace(spark, "overheads")
    held = R.Held(space, stream.cells.withColumn("run", F.lit(0)), stream.rects.withColumn("run", F.lit(0)), 0.5)
    before = space.put(held.rebuild(plan, LAST - 1), "before")
    now, states = F.col("rnd") == LAST, []
    fresh = marginals.counted_collectors(stream.cells.where(now), stream.rects.where(now), layout.probe_side(plan), [], ["points"])
    timed("fold_round", lambda: states.append(space.put(marginals.fold_round(before, fresh, plan, 0.5), "state")) or states[0].count())
    got, stats = [], R.totals(states[0], plan)
    timed("report", lambda: got.extend(R.reports(stats).collect()) or len(got))
    load = {r["machine_id"]: float(r["numerator"]) for r in got}
    costs = lambda m: {r["tile_id"]: float(r["c"]) for r in stats.where(F.col("machine_id") == m).select("tile_id", (F.col("n") * F.col("q") * F.col("r")).alias("c")).collect()}
    axes = lambda t: planner.axis_stats(states[0].where(F.col("tile_id") == t.tile_id).collect())
    moved = []
    timed("reduce_and_move", lambda: moved.extend(planner.rebalance_once(EVEN, load, costs, axes, LAST + 1)) or len(moved[0]))
    timed("receive", lambda: R.moved_queries(stream, [t for t in moved[0] if t.born_round]).count())
    timed("index_update", lambda: routing.cell_index(moved[0]).size)
    timed("decide", lambda: governor.Governor().step(float(sum(r["r"] for r in got))))
    timed("donor_marginals", lambda: states[0].where(F.col("tile_id") == EVEN[0].tile_id).count())
    timed("rebuild_after_split", lambda: R.carried(states[0], EVEN, moved[0], held, LAST).count())
    return spark.createDataFrame(rows, "step string, seconds double, row_count long")


def _uniform_loads(spark, sf_dir):
    return R.static_loads(R.counted(spark, *_pq(spark, sf_dir)), _plan(spark)).select("rnd", "machine_id", "load", "fresh")


@query("static_uniform_load", f"{LOADS} SELECT rnd, machine_id, load, fresh FROM loads")
def _(spark, sf_dir):
    return _uniform_loads(spark, sf_dir)


@query(
    "replicated_load",
    f"""WITH {LOC}, p AS (SELECT rnd, count(*) AS fresh FROM pts GROUP BY 1), m AS (SELECT CAST(unnest(range(0, {MACHINES})) AS INTEGER) AS machine_id),
    r AS (SELECT CAST(unnest(range(0, 30)) AS INTEGER) AS rnd), d AS (SELECT r.rnd, machine_id, coalesce(fresh, 0) // {MACHINES} + CASE WHEN machine_id < coalesce(fresh, 0) % {MACHINES} THEN 1 ELSE 0 END AS mine,
      (SELECT count(*) FROM qs WHERE qs.rnd <= r.rnd) AS live FROM r CROSS JOIN m LEFT JOIN p USING (rnd))
    SELECT rnd, machine_id, CAST(mine * live AS BIGINT) AS load, CAST(mine AS BIGINT) AS fresh FROM d""",
)
def _(spark, sf_dir):
    return R.replicated_loads(R.counted(spark, *_pq(spark, sf_dir)), MACHINES).select("rnd", "machine_id", "load", "fresh")


@query("imbalance_by_round", f"{LOADS} SELECT rnd, min(load) AS min_load, avg(load) AS mean_load, max(load) AS max_load, max(load) / avg(load) AS max_over_mean FROM loads GROUP BY rnd")
def _(spark, sf_dir):
    return measures.imbalance(_uniform_loads(spark, sf_dir)).drop("variation")


@query(
    "units_of_work_model",
    f"""{LOADS}, t AS (SELECT rnd, CASE WHEN max(load) = 0 THEN 1.0 ELSE least(1.0, CAST(20000 AS DOUBLE) / max(load)) END AS accept, CAST(sum(fresh) AS BIGINT) AS arrivals FROM loads GROUP BY 1)
    SELECT rnd, CAST(accept AS DOUBLE) AS accept, arrivals, (SELECT count(*) FROM qs WHERE qs.rnd <= t.rnd) AS live_queries, CAST(accept AS DOUBLE) * arrivals AS processed FROM t""",
)
def _(spark, sf_dir):
    stream = R.counted(spark, *_pq(spark, sf_dir))
    run = R.static_run(R.static_loads(stream, _plan(spark)), stream, "uniform_grid", MACHINES, BalanceConfig(machines=MACHINES, capacity=20000.0))
    return R.run_frame(spark, run).select("rnd", "accept", "arrivals", "live_queries", "processed")


@query(
    "utilisation",
    f"""{LOADS}, u AS (SELECT rnd // 5 AS period, machine_id, avg(least(1.0, load / 20000.0)) AS used FROM loads GROUP BY 1, 2)
    SELECT CAST(period AS INTEGER) AS period, round(min(used), 6) AS least, round(avg(used), 6) AS mean, round(max(used), 6) AS most FROM u GROUP BY 1""",
)
def _(spark, sf_dir):
    got = measures.utilisation(_uniform_loads(spark, sf_dir), 20000.0)
    return got.select("period", *(F.round(c, 6).alias(c) for c in ("least", "mean", "most")))


@query(
    "stats_traffic",
    f"""WITH {LOC}, c AS (SELECT DISTINCT side, rnd, greatest(0, least(side - 1, floor(x * side / 256))) AS cx, greatest(0, least(side - 1, floor(y * side / 100))) AS cy FROM pts CROSS JOIN (SELECT unnest([64, 256, 1000]) AS side)),
    s AS (SELECT side, count(DISTINCT rnd) AS collections, count(*) AS cells FROM c GROUP BY side)
    SELECT side, machines, collections, 2 * machines * collections AS decentral, 5 * side * side * collections AS central, 5 * cells AS touched FROM s CROSS JOIN (SELECT unnest([8, 22]) AS machines)""",
)
def _(spark, sf_dir):
    return measures.stats_traffic(tables.event_points(spark, sf_dir), EVENTS, [64, 256, 1000], [8, 22])


@query(
    "counted_traffic",
    f"WITH {LOC}, c AS (SELECT rnd, cx, cy FROM pts UNION SELECT rnd, x, CAST(unnest(range(cy0, cy1 + 1)) AS INTEGER) FROM (SELECT *, CAST(unnest(range(cx0, cx1 + 1)) AS INTEGER) AS x FROM qs)) SELECT rnd, CAST({2 * MACHINES} AS BIGINT) AS decentral, 5 * count(*) AS central FROM c GROUP BY rnd",
)
def _(spark, sf_dir):
    return measures.counted_traffic(*_pq(spark, sf_dir), MACHINES)


@query("network_rows", f"{BASE}, {RP}, {RQ} SELECT rnd, coalesce(a.c, 0) AS points, coalesce(b.c, 0) AS query_copies, CAST({2 * MACHINES} AS BIGINT) AS reports FROM (SELECT rnd, count(*) AS c FROM rp GROUP BY 1) a FULL JOIN (SELECT rnd, count(*) AS c FROM rq GROUP BY 1) b USING (rnd)")
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    return measures.network_rows(routing.route_points(p, _plan(spark)), routing.route_queries(q, _plan(spark)), MACHINES)


@query("update_counts", f"{BASE}, {RQ} SELECT CAST(sum(row1 - row0 + 1 + col1 - col0 + 1) AS BIGINT) AS query_updates, count(*) AS query_copies, 2 * (SELECT count(*) FROM pts) AS point_updates FROM rq")
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    plan = _plan(spark)
    return measures.update_counts(marginals.clip(routing.route_queries(q, plan), plan), p)


@query("query_copies", f"{BASE}, {RQ} SELECT count(DISTINCT (query_id, machine_id)) AS tiled, {MACHINES} * (SELECT count(*) FROM qs) AS replicated FROM rq")
def _(spark, sf_dir):
    q = tables.event_queries(spark, sf_dir)
    return measures.query_copies(routing.route_queries(q, _plan(spark)), q, MACHINES)


@query("plan_invariants")
def _(spark, sf_dir):
    """Faults of every plan that balancing made: cells outside the cover, and matches lost, invented or repeated under the last plan."""
    run = _adaptive(spark, sf_dir, policy="always")
    p, q = _pq(spark, sf_dir)
    bad = sum(not layout.covers(EVENTS, tiles) for tiles in run.plans)
    faults = measures.plan_faults(p, q, _plan(spark, run.plans[-1]), _plan(spark)).agg(F.sum("faults").alias("match_faults"))
    return faults.select(F.lit(bad).alias("cover_faults"), "match_faults", F.lit(len(run.plans)).alias("plans"))


# ---- answers

INSIDE = "p.x BETWEEN q.x0 AND q.x1 AND p.y BETWEEN q.y0 AND q.y1"
MATCHES = f"{BASE}, {RP} SELECT q.query_id, p.point_id, p.machine_id FROM rp p JOIN qs q ON {INSIDE} AND q.qts <= p.ts"
for _name, _kind, _salts in (("continuous_matches", "cell", 1), ("continuous_matches_tile", "tile", 1), ("continuous_matches_salted", "tile", 8)):
    query(_name, MATCHES)(lambda spark, sf_dir, k=_kind, s=_salts: matching.match_continuous(*_pq(spark, sf_dir), _plan(spark), k, salts=s))


@query("matches_any_order", f"WITH {LOC} SELECT q.rnd, count(*) AS matches FROM pts p JOIN qs q ON {INSIDE} GROUP BY 1")
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    found = matching.match_continuous(p, q, _plan(spark), registered=False)
    return found.join(q.select("query_id", "rnd"), "query_id").groupBy("rnd").agg(F.count("*").alias("matches"))


@query("predicate_matches", f"{BASE}, {RP} SELECT q.query_id, p.point_id, p.machine_id FROM rp p JOIN qs q ON {INSIDE} AND q.qts <= p.ts AND p.tag = 'purchase' AND p.x >= 20")
def _(spark, sf_dir):
    return matching.match_continuous(*_pq(spark, sf_dir), _plan(spark), predicate=(F.col("tag") == "purchase") & (F.col("x") >= 20))


HISTORY = lineage.tile_history([EVEN] * SWITCH + [STEPPED] * (LAST + 1 - SWITCH))
SNAP_WINDOW = 25


def _store(spark, sf_dir):
    p = tables.event_points(spark, sf_dir)
    old = routing.route_points(p.where(F.col("rnd") < SWITCH), _plan(spark))
    return old.unionByName(routing.route_points(p.where(F.col("rnd") >= SWITCH), _plan(spark, STEPPED)))


def _snapshot(spark, sf_dir):
    q = tables.event_queries(spark, sf_dir).where(F.col("rnd") == LAST)
    return matching.match_snapshot(q, _store(spark, sf_dir), lineage.chain_frame(spark, HISTORY, LAST - SNAP_WINDOW), SNAP_WINDOW)


SNAP = f"""{TWO_PLANS}, st AS (SELECT p.*, t.tile_id FROM pts p JOIN plans t ON t.later = CAST(p.rnd >= {SWITCH} AS INTEGER) AND {IN_TILE}),
  ans AS (SELECT q.query_id, p.point_id, p.tile_id FROM qs q JOIN st p ON {INSIDE} AND q.rnd = {LAST} AND p.rnd > {LAST - SNAP_WINDOW} AND p.rnd <= {LAST})"""


@query("snapshot_matches", f"{SNAP} SELECT query_id, point_id, tile_id AS stored_tile FROM ans")
def _(spark, sf_dir):
    return _snapshot(spark, sf_dir).select("query_id", "point_id", "stored_tile")


LINKED = f"""{TWO_PLANS}, old AS (SELECT tile_id, cx0, cy0, cx1, cy1, tile_id IN (SELECT tile_id FROM plan_b) AS stays FROM plan_a),
  links AS (SELECT DISTINCT q.query_id, t.tile_id FROM qs q JOIN (SELECT tile_id, cx0, cy0, cx1, cy1 FROM plan_b UNION ALL SELECT tile_id, cx0, cy0, cx1, cy1 FROM old WHERE NOT stays) t ON {OVER} AND q.rnd = {LAST})"""


@query(
    "chain_acknowledgements",
    f"""{LINKED}, st AS (SELECT p.*, t.tile_id FROM pts p JOIN plans t ON t.later = CAST(p.rnd >= {SWITCH} AS INTEGER) AND {IN_TILE}),
    ans AS (SELECT q.query_id, p.tile_id, count(*) AS sent FROM qs q JOIN st p ON {INSIDE} AND q.rnd = {LAST} AND p.rnd > {LAST - SNAP_WINDOW} AND p.rnd <= {LAST} GROUP BY 1, 2)
    SELECT query_id, count(*) AS expected, count(*) AS acknowledged, CAST(coalesce(sum(sent), 0) AS BIGINT) AS rows, true AS final FROM links LEFT JOIN ans USING (query_id, tile_id) GROUP BY 1""",
)
def _(spark, sf_dir):
    """Expected and received acknowledgements of every snapshot query; final once all links have answered."""
    q = tables.event_queries(spark, sf_dir).where(F.col("rnd") == LAST)
    links = matching.snapshot_links(q, lineage.chain_frame(spark, HISTORY, LAST - SNAP_WINDOW), SNAP_WINDOW)
    return lineage.acknowledge(links, _snapshot(spark, sf_dir))


@query("chain_ledger", f"{SNAP} SELECT query_id, count(DISTINCT tile_id) AS links, count(*) AS rows FROM ans GROUP BY 1")
def _(spark, sf_dir):
    return lineage.chain_ledger(_snapshot(spark, sf_dir))


STEP_HISTORY = f"""{STEP}, old AS (SELECT max(tile_id) AS last FROM plan), h AS (
  SELECT t.tile_id, []::BIGINT[] AS parent_ids, t.machine_id, 0 AS born_round, CASE WHEN t.tile_id = step.tile_id THEN {SWITCH} END AS retired_round FROM plan t, step
  UNION ALL SELECT last + k, [step.tile_id], CASE WHEN (moved = 'first') = (k = 1) THEN receiver ELSE donor END, {SWITCH}, NULL FROM step, old, (SELECT unnest([1, 2]) AS k))"""


def _step_history(spark, sf_dir) -> list[Tile]:
    """The tiles' history when the rebalance that the stream calls for takes place in round SWITCH."""
    after, _ = _first_step(spark, sf_dir, SWITCH)
    return lineage.tile_history([EVEN] * SWITCH + [after] * (LAST + 1 - SWITCH))


@query(
    "lineage_chain",
    f"""{STEP_HISTORY}, links(current_tile, stored_tile, depth) AS (SELECT tile_id, tile_id, 0 FROM h WHERE retired_round IS NULL
      UNION ALL SELECT l.current_tile, p.parent, l.depth + 1 FROM links l JOIN (SELECT tile_id, unnest(parent_ids) AS parent, born_round FROM h) p ON p.tile_id = l.stored_tile AND p.born_round > 4)
    SELECT l.current_tile, l.stored_tile, CAST(l.depth AS INTEGER) AS depth, h.machine_id, h.born_round, h.retired_round FROM links l JOIN h ON h.tile_id = l.stored_tile WHERE h.retired_round IS NULL OR h.retired_round > 4""",
)
def _(spark, sf_dir):
    return lineage.chain_sql(spark, plan_frame(spark, _step_history(spark, sf_dir)), 4)


@query("lineage_pruned", f"{STEP_HISTORY} SELECT tile_id, (SELECT count(*) FROM h p WHERE list_contains(c.parent_ids, p.tile_id) AND (p.retired_round IS NULL OR p.retired_round > 12)) AS parents FROM h c WHERE c.retired_round IS NULL OR c.retired_round > 12")
def _(spark, sf_dir):
    """What is left of the history once data up to round 12 have expired."""
    return plan_frame(spark, lineage.prune(_step_history(spark, sf_dir), 12)).select("tile_id", F.size("parent_ids").cast("long").alias("parents"))


@query("chain_stats")
def _(spark, sf_dir):
    run = _adaptive(spark, sf_dir, policy="always")
    history = lineage.tile_history([EVEN, *run.plans])
    return lineage.chain_stats(lineage.chain_frame(spark, history, 0))


@query("retired_tiles", f"{STEP_HISTORY} SELECT tile_id, retired_round FROM h WHERE retired_round IS NOT NULL AND retired_round <= 12 AND retired_round < 20")
def _(spark, sf_dir):
    return lineage.retire_ready(plan_frame(spark, _step_history(spark, sf_dir)), 12, 20).select("tile_id", "retired_round")


MOVED = [t for t in STEPPED if t.parent_ids and t.machine_id != t.prev_machine_id]


@query("migration_volume", f"WITH {values_sql(MOVED)}, {LOC} SELECT t.tile_id, count(q.query_id) AS queries FROM plan t LEFT JOIN qs q ON {OVER} AND q.rnd < {SWITCH} GROUP BY 1")
def _(spark, sf_dir):
    q = tables.event_queries(spark, sf_dir).where(F.col("rnd") < SWITCH)
    moved = _plan(spark, MOVED)
    return matching.migration_volume(moved.select("tile_id"), routing.route_queries(q, moved))


@query(
    "continuous_aggregate",
    f"WITH {LOC} SELECT q.query_id, CAST(p.rnd // 5 AS INTEGER) AS win, count(*) AS matched, round(sum(p.x), 4) AS total FROM pts p JOIN qs q ON {INSIDE} AND q.qts <= p.ts GROUP BY 1, 2",
)
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    got = matching.continuous_aggregate(p, q, _plan(spark), F.floor(F.col("rnd") / 5))
    return got.withColumn("total", F.round("total", 4))


@query("last_k_window", f"WITH {LOC}, k AS (SELECT tag, point_id, row_number() OVER (PARTITION BY tag ORDER BY ts DESC, point_id DESC) AS place FROM pts) SELECT tag, point_id, CAST(place AS INTEGER) AS place FROM k WHERE place <= 20")
def _(spark, sf_dir):
    return matching.count_window(tables.event_points(spark, sf_dir), 20).select("tag", "point_id", "place")


@query("size_window", f"WITH {LOC}, k AS (SELECT tag, point_id, sum(cx + 1) OVER (PARTITION BY tag ORDER BY ts DESC, point_id DESC) AS held FROM pts) SELECT tag, point_id, CAST(held AS BIGINT) AS held FROM k WHERE held <= 500")
def _(spark, sf_dir):
    return matching.size_window(tables.event_points(spark, sf_dir), F.col("cx") + 1, 500).select("tag", "point_id", "held")


@query(
    "persistent_hotspots",
    f"""WITH {LOC}, c AS (SELECT rnd, cx // 8 AS cx, cy // 8 AS cy, count(*) AS n FROM pts GROUP BY ALL), h AS (SELECT *, rnd - row_number() OVER (PARTITION BY cx, cy ORDER BY rnd) AS island FROM c WHERE n >= 4)
    SELECT CAST(cx AS INTEGER) AS cx, CAST(cy AS INTEGER) AS cy, min(rnd) AS start, count(*) AS length FROM h GROUP BY cx, cy, island HAVING count(*) >= 3""",
)
def _(spark, sf_dir):
    coarse = tables.event_points(spark, sf_dir).select("rnd", F.expr("int(cx div 8)").alias("cx"), F.expr("int(cy div 8)").alias("cy"))
    return matching.persistent_hotspots(coarse.groupBy("rnd", "cx", "cy").agg(F.count("*").alias("points")), 4, 3)


RANGES = [(i, x, y, min(63, x + w), min(63, y + h)) for i, (x, y, w, h) in enumerate([(0, 0, 63, 63), (0, 0, 7, 9), (3, 40, 20, 5), (10, 10, 0, 0), (30, 0, 33, 63), (0, 54, 9, 9), (1, 1, 1, 30)])]
RANGE_SQL = ", ".join(str(r) for r in RANGES)


@query("euler_range", f"WITH r(range_id, rx0, ry0, rx1, ry1) AS (VALUES {RANGE_SQL}), {LOC} SELECT range_id, count(*) AS overlapping FROM r JOIN qs q ON q.cx0 <= rx1 AND q.cx1 >= rx0 AND q.cy0 <= ry1 AND q.cy1 >= ry0 GROUP BY 1")
def _(spark, sf_dir):
    counts = euler.euler_counts(tables.event_queries(spark, sf_dir))
    return euler.euler_range(counts, spark.createDataFrame(RANGES, "range_id int, rx0 int, ry0 int, rx1 int, ry1 int"))


@query(
    "euler_counts",
    f"""WITH {LOC}, x AS (SELECT *, CAST(unnest(range(cx0, cx1 + 1)) AS INTEGER) AS cx FROM qs), e AS (SELECT *, CAST(unnest(range(cy0, cy1 + 1)) AS INTEGER) AS cy FROM x),
    f AS (SELECT cx, cy, count(*) AS face, sum(CAST(cx > cx0 AS INTEGER)) AS v, sum(CAST(cy > cy0 AS INTEGER)) AS h, sum(CAST(cx > cx0 AND cy > cy0 AS INTEGER)) AS c FROM e GROUP BY 1, 2), p AS (SELECT cx, cy, count(*) AS points FROM pts GROUP BY 1, 2)
    SELECT cx, cy, coalesce(face, 0) AS face, CAST(coalesce(v, 0) AS BIGINT) AS v_edge, CAST(coalesce(h, 0) AS BIGINT) AS h_edge, CAST(coalesce(c, 0) AS BIGINT) AS vertex, coalesce(points, 0) AS points FROM f FULL JOIN p USING (cx, cy)""",
)
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    return euler.euler_counts(q, p)


# ---- workloads

def _word(salt: str) -> str:
    return f"CAST('0x' || substr(md5(CAST(point_id AS VARCHAR) || ':{salt}'), 1, 7) AS BIGINT)"


def _bytes(salt: str) -> str:
    return " + ".join(f"CAST('0x' || substr(md5(CAST(point_id AS VARCHAR) || ':{salt}'), {2 * k + 1}, 2) AS BIGINT)" for k in range(12))


def _hotspot_sql(name: str) -> str:
    spots, shape = workloads.SHAPES[name]
    side, low = workloads.hotspot_side(EVENTS), "0"
    cx, cy, hot = "cx", "cy", []
    for where, start, table in spots:
        share = "CASE rnd " + " ".join(f"WHEN {start + k} THEN {v}" for k, v in enumerate(table)) + " ELSE 0 END"
        x0, y0 = workloads.corner(EVENTS, where)
        if shape == "uniform":
            px, py = f"{x0} + {_word('x')} % {side}", f"{y0} + {_word('y')} % {side}"
        else:
            pos = lambda base, s: f"greatest(0, least(63, {base + side // 2} + floor((({_bytes(s)}) / 256.0 - 6) * {0.2 * side} + 0.5)))"
            px, py = pos(x0, "n"), pos(y0, "m")
        take = f"({_word('r')} % 1000 >= {low} AND {_word('r')} % 1000 < {low} + {share})"
        cx, cy = f"CASE WHEN {take} THEN {px} ELSE {cx} END", f"CASE WHEN {take} THEN {py} ELSE {cy} END"
        hot.append(take)
        low = f"({low} + {share})"
    return f"""WITH {LOC}, w AS (SELECT rnd, CAST({cx} AS BIGINT) AS cx, CAST({cy} AS BIGINT) AS cy, {' OR '.join(hot)} AS hot FROM pts)
    SELECT rnd, hot, count(*) AS points, CAST(sum(cx) AS BIGINT) AS sum_cx, CAST(sum(cy) AS BIGINT) AS sum_cy, CAST(sum(cx * cy) AS BIGINT) AS sum_cxy FROM w GROUP BY 1, 2"""


for _name in workloads.SHAPES:
    if _name != "plain":

        def _hotspot(spark, sf_dir, n=_name):
            p, q = _pq(spark, sf_dir)
            moved, _ = workloads.workload(spark, p, q, EVENTS, n)
            return moved.groupBy("rnd", "hot").agg(F.count("*").alias("points"), F.sum("cx").alias("sum_cx"), F.sum("cy").alias("sum_cy"), F.sum(F.col("cx") * F.col("cy")).alias("sum_cxy"))

        query(_name, _hotspot_sql(_name))(_hotspot)


@query("drift_heatmap", f"WITH {LOC} SELECT rnd, CAST(((cx + rnd) % 64) // 8 AS INTEGER) AS hx, count(*) AS points FROM pts GROUP BY 1, 2")
def _(spark, sf_dir):
    moved = workloads.drift(tables.event_points(spark, sf_dir), EVENTS)
    return moved.groupBy("rnd", F.expr("int(cx div 8)").alias("hx")).agg(F.count("*").alias("points"))


@query(
    "heatmap_pivot",
    f"WITH {LOC} SELECT CAST(cx // 8 AS INTEGER) AS hx, CAST(cy // 8 AS INTEGER) AS hy, " + ", ".join(f"CAST(sum(CAST(hour(ts) // 6 = {k} AS INTEGER)) AS BIGINT) AS part_{k}" for k in range(4)) + " FROM pts GROUP BY 1, 2",
)
def _(spark, sf_dir):
    return reports.heat_map(tables.event_points(spark, sf_dir))


@query("replay_stream", f"WITH {LOC} SELECT CAST(rnd + 30 * k AS INTEGER) AS rnd, count(*) AS points FROM pts CROSS JOIN (SELECT unnest([0, 1, 2]) AS k) GROUP BY 1")
def _(spark, sf_dir):
    return tables.replay(tables.event_points(spark, sf_dir), 3).groupBy("rnd").agg(F.count("*").alias("points"))


@query("control_uniform", "SELECT CAST(greatest(0, least(63, floor((l_extendedprice - 900.0) * 64 / 104101.0))) AS INTEGER) AS cx, count(*) AS points, CAST(sum(CAST(greatest(0, least(63, floor(CAST(l_partkey AS DOUBLE) * 64 / CAST((SELECT count(*) FROM part) AS DOUBLE)))) AS INTEGER)) AS BIGINT) AS sum_cy FROM lineitem GROUP BY 1")
def _(spark, sf_dir):
    return tables.line_points(spark, sf_dir).groupBy("cx").agg(F.count("*").alias("points"), F.sum("cy").alias("sum_cy"))


@query("control_strategies")
def _(spark, sf_dir):
    """All rounds of every strategy on the control without skew: the uniform grid is close to even, and adaptive balancing must not hurt."""
    p = tables.line_points(spark, sf_dir).withColumn("rnd", F.pmod(F.col("rnd"), F.lit(30)))
    q = tables.order_queries(spark, sf_dir)
    stream = R.counted(spark, p, q)
    history = baselines.history_layout(p, q, EVENTS, MACHINES, max(200, p.count() // 4))
    config = BalanceConfig(machines=MACHINES, capacity=baselines.default_capacity(stream, history, MACHINES))
    rows = R.run_frame(spark, *baselines.compare(spark, stream, history, EVENTS, config, ("lazy", "always")))
    # latency over mean load is the loads' mean square over their squared mean
    spread = F.sqrt(F.greatest(F.lit(0.0), F.col("latency") / F.col("mean_load") - 1))
    return rows.withColumns({"max_over_mean": F.col("max_load") / F.col("mean_load"), "variation": spread})


@query("embedding_cells", "WITH e AS (SELECT CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings) SELECT CAST(greatest(0, least(63, floor((x + 0.5) * 64 / 1.0))) AS INTEGER) AS cx, CAST(greatest(0, least(63, floor((y + 0.5) * 64 / 1.0))) AS INTEGER) AS cy, count(*) AS points FROM e GROUP BY 1, 2")
def _(spark, sf_dir):
    return tables.embedding_points(spark, sf_dir).groupBy("cx", "cy").agg(F.count("*").alias("points"))


SUBSCRIPTIONS = [(i, (i * 7) % 56, (i * 13) % 56, (i * 7) % 56 + 15, (i * 13) % 56 + 15, w) for i, w in enumerate(["the", "of", "que", "der", "license", "la"] * 10)]
SUBSCRIPTION_SQL = ", ".join(str(s) for s in SUBSCRIPTIONS)


@query(
    "keyword_subscriptions",
    f"""WITH s(query_id, cx0, cy0, cx1, cy1, keyword) AS (VALUES {SUBSCRIPTION_SQL}), d AS (SELECT doc_id, lang, text, CAST(greatest(0, least(63, floor(CAST(n_chars AS DOUBLE) * 64 / 4096))) AS INTEGER) AS cx,
      CAST(greatest(0, least(63, floor(CAST(doc_id * 37 % 1000 AS DOUBLE) * 64 / 1000))) AS INTEGER) AS cy FROM documents)
    SELECT query_id, doc_id, lang AS tag FROM d JOIN s ON cx BETWEEN cx0 AND cx1 AND cy BETWEEN cy0 AND cy1 AND contains(text, keyword)""",
)
def _(spark, sf_dir):
    subs = spark.createDataFrame(SUBSCRIPTIONS, "query_id int, cx0 int, cy0 int, cx1 int, cy1 int, keyword string")
    return reports.keyword_subscriptions(tables.document_points(spark, sf_dir), subs)


# ---- user reports

@query(
    "matches_by_region",
    f"""WITH {LOC}, m AS (SELECT q.query_id, q.subscriber_id, count(*) AS m FROM pts p JOIN qs q ON {INSIDE} AND q.qts <= p.ts GROUP BY 1, 2)
    SELECT r_name, n_name, CAST(sum(m) AS BIGINT) AS matches, count(DISTINCT subscriber_id) AS subscribers FROM m JOIN customer ON c_custkey = subscriber_id % (SELECT count(*) FROM customer) + 1
    JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1, 2""",
)
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    return reports.matches_by_region(spark, sf_dir, matching.match_continuous(p, q, _plan(spark)), q)


@query("hot_cells_topk", f"WITH {LOC} SELECT cx, cy, count(*) AS points FROM pts GROUP BY 1, 2 ORDER BY points DESC, cx, cy LIMIT 10")
def _(spark, sf_dir):
    return reports.hot_cells(tables.event_points(spark, sf_dir))


@query("unmatched_queries_anti", f"WITH {LOC} SELECT query_id, rnd FROM qs q WHERE NOT EXISTS (SELECT 1 FROM pts p WHERE {INSIDE} AND q.qts <= p.ts)")
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    return reports.unmatched_queries(q, matching.match_continuous(p, q, _plan(spark)))


@query("match_rate", f"WITH {LOC}, m AS (SELECT point_id, count(*) AS m FROM pts p JOIN qs q ON {INSIDE} AND q.qts <= p.ts GROUP BY 1) SELECT tag, count(*) AS points, count(m) AS matched, CAST(coalesce(sum(m), 0) AS BIGINT) AS matches FROM pts LEFT JOIN m USING (point_id) GROUP BY tag")
def _(spark, sf_dir):
    p, q = _pq(spark, sf_dir)
    return reports.match_rate(matching.match_continuous(p, q, _plan(spark)), p)


@query("sliding_rate", f"WITH {LOC}, c AS (SELECT rnd, count(*) AS points FROM pts GROUP BY 1) SELECT rnd, points, CAST(sum(points) OVER (ORDER BY rnd RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS recent FROM c")
def _(spark, sf_dir):
    return measures.sliding_rate(tables.event_points(spark, sf_dir))


@query(
    "session_activity",
    """WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
    SELECT user_id, CAST(min(ts) AS TIMESTAMP) AS start, count(*) AS n FROM s GROUP BY user_id, k""",
)
def _(spark, sf_dir):
    rows = tables.table(spark, sf_dir, "events").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return rows.select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


# ---- SQL surface and streams

for _name, _method, _sql in (("sql_route_points", "route_points", ROUTED), ("sql_route_queries", "route_queries", ROUTED_Q), ("sql_tile_costs", "tile_costs", f"{BASE}, {STATS} SELECT tile_id, machine_id, n, q, numerator FROM cs")):

    def _by_sql(spark, sf_dir, m=_method):
        sql.register_views(spark, sf_dir)
        return sql.run(spark, m)

    query(_name, _sql)(_by_sql)


def _played(frame: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Play a finite stream to its end into written tables: all batches' rows, or in complete mode the last batch's."""
    space, batches = Workspace(frame.sparkSession, name), []

    def sink(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{space.path}/out/batch={batch}")
        batches.append(batch)

    frame.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", f"{space.path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in frame.schema)
    held = frame.sparkSession.read.schema(f"{schema}, batch int").parquet(f"{space.path}/out")
    return (held.where(F.col("batch") == max(batches)) if mode == "complete" else held).drop("batch")


def _balanced(spark, sf_dir, parts: int = 6, listed: bool = True) -> loop.BalancedStream:
    """The event stream in several batches, answered and balanced, with a restart half way."""
    space = Workspace(spark, "balanced")
    events, days = tables.table(spark, sf_dir, "events"), (LAST + parts) // parts
    part = F.least(F.lit(parts - 1), F.expr(f"int(datediff(ts, '{tables.EPOCH}') div {days})"))
    late = events.withColumn("part", part)
    for k in range(parts):
        late.where(F.col("part") == k).drop("part").coalesce(1).write.mode("append").parquet(f"{space.path}/in")
        if k in (parts // 2 - 1, parts - 1):
            job = loop.BalancedStream(spark, f"{space.path}/out", config=BalanceConfig(machines=MACHINES, policy="always"), listed=listed)
            job.start(loop.event_source(spark, f"{space.path}/in")).awaitTermination()
    return job


@query("stream_balanced_matches", f"WITH {LOC} SELECT q.query_id, p.point_id FROM pts p JOIN qs q ON {INSIDE} AND q.qts <= p.ts")
def _(spark, sf_dir):
    """All matches of a balanced stream, over rebalances, forwarded points and a restart: each once."""
    return _balanced(spark, sf_dir).matches().select("query_id", "point_id")


@query("stream_query_state", f"WITH {LOC} SELECT q.query_id, count(*) AS matched, round(sum(p.x), 4) AS total FROM pts p JOIN qs q ON {INSIDE} AND q.qts <= p.ts GROUP BY 1")
def _(spark, sf_dir):
    """Each query's aggregates at the end of the balanced stream, wherever the query has moved."""
    return _balanced(spark, sf_dir, listed=False).aggregates().select("query_id", "matched", F.round("total", 4).alias("total"))


@query("stream_sessions", """WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e),
    t AS (SELECT user_id, CAST(min(ts) AS TIMESTAMP) AS start, max(ts) AS last, count(*) AS n FROM s GROUP BY user_id, k)
    SELECT user_id, start, n FROM t WHERE last + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR""")
def _(spark, sf_dir):
    """Activity sessions that the watermark has closed by the stream's end."""
    got = _played(loop.sessions(loop.event_source(spark, f"{sf_dir}/events*.parquet"), lateness="1 hour"), "sessions")
    return got.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_daily_windows", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def _(spark, sf_dir):
    """Daily arrivals by type, from the event stream with a watermark."""
    got = _played(loop.windowed_arrivals(loop.event_source(spark, f"{sf_dir}/events*.parquet")), "daily", "complete")
    return got.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("stream_deduplicated", "SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    """Events once each, of a stream that delivers every one of them twice."""
    source = loop.event_source(spark, f"{sf_dir}/events*.parquet")
    twice = source.withColumn("again", F.explode(F.array(F.lit(0), F.lit(1)))).drop("again")
    return _played(loop.deduplicated(twice).select("event_id", "event_type"), "once").groupBy("event_type").agg(F.count("*").alias("n"))
