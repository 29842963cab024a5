"""Row and column statistics of tiles.

``clip`` gives every routed query its rows and columns inside a tile; collectors
count a round's arrivals, and folding turns them into cumulative marginals:
for index i of an axis, ``n``/``q``/``r`` are (faded) points, query starts and
recent arrivals at or before i, ``span_q`` the queries that reach i from before.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridtide.plans.layout import probe_side, small

KEY = ["rnd", "tile_id", "axis", "idx"]


def in_tile(points: DataFrame, plan: DataFrame) -> DataFrame:
    """Routed points with their local row and column."""
    full = points.join(small(probe_side(plan).drop("machine_id")), "tile_id")
    return full.select("rnd", "tile_id", (F.col("cy") - F.col("t_cy0")).alias("row"), (F.col("cx") - F.col("t_cx0")).alias("col"))


def clip(queries: DataFrame, plan: DataFrame) -> DataFrame:
    """Routed queries with first and last local row and column of their overlap with the tile."""
    full = queries.join(small(probe_side(plan).drop("machine_id")), "tile_id")
    low = lambda a, b: F.greatest(F.col(a), F.col(b)) - F.col(b)
    high = lambda a, b, base: F.least(F.col(a), F.col(b)) - F.col(base)
    return full.select(
        "rnd", "tile_id", "query_id",
        low("cy0", "t_cy0").alias("row0"), high("cy1", "t_cy1", "t_cy0").alias("row1"),
        low("cx0", "t_cx0").alias("col0"), high("cx1", "t_cx1", "t_cx0").alias("col1"),
    )


def _axes(row: Column, col: Column, name: str = "idx") -> Column:
    return F.explode(F.array(F.struct(F.lit("row").alias("axis"), row.alias(name)), F.struct(F.lit("col").alias("axis"), col.alias(name)))).alias("a")


def collect_points(local: DataFrame) -> DataFrame:
    """One row and one column counter for each point."""
    return local.select("rnd", "tile_id", _axes(F.col("row"), F.col("col"))).select("rnd", "tile_id", "a.*").groupBy(*KEY).agg(F.count("*").alias("points"))


def collect_query_starts(clipped: DataFrame) -> DataFrame:
    """The row and the column of each query's first cell in the tile."""
    return clipped.select("rnd", "tile_id", _axes(F.col("row0"), F.col("col0"))).select("rnd", "tile_id", "a.*").groupBy(*KEY).agg(F.count("*").alias("starts"))


def collect_query_spans(clipped: DataFrame, method: str = "explode") -> DataFrame:
    """Every later row and column that each query enters.

    ``explode`` makes a row for each of them; ``delta`` two rows a query (+1
    where the span begins, -1 behind its end) and a running sum.
    """
    both = F.explode(
        F.array(
            F.struct(F.lit("row").alias("axis"), F.col("row0").alias("a"), F.col("row1").alias("b")),
            F.struct(F.lit("col").alias("axis"), F.col("col0").alias("a"), F.col("col1").alias("b")),
        )
    ).alias("s")
    spans = clipped.select("rnd", "tile_id", both).select("rnd", "tile_id", "s.*").where("b > a")
    if method == "explode":
        return spans.withColumn("idx", F.explode(F.sequence(F.col("a") + 1, F.col("b")))).groupBy(*KEY).agg(F.count("*").alias("spans"))
    steps = F.explode(F.array(F.struct((F.col("a") + 1).alias("idx"), F.lit(1).alias("d")), F.struct((F.col("b") + 1).alias("idx"), F.lit(-1).alias("d")))).alias("e")
    delta = spans.select("rnd", "tile_id", "axis", steps).select("rnd", "tile_id", "axis", "e.*").groupBy(*KEY).agg(F.sum("d").alias("d"))
    group = Window.partitionBy("rnd", "tile_id", "axis").orderBy("idx")
    run = delta.withColumn("spans", F.sum("d").over(group)).withColumn("next", F.lead("idx").over(group))
    return run.where("spans > 0").withColumn("idx", F.explode(F.sequence(F.col("idx"), F.col("next") - 1))).select(*KEY, "spans")


def collectors(local: DataFrame, clipped: DataFrame) -> DataFrame:
    """All three collectors side by side, zero where nothing arrived."""
    p, s, t = collect_points(local), collect_query_starts(clipped), collect_query_spans(clipped, "delta")
    zero = lambda frame, have: frame.select(*KEY, *(F.col(c).cast("long").alias(c) if c == have else F.lit(0).cast("long").alias(c) for c in ("points", "starts", "spans")))
    rows = zero(p, "points").unionByName(zero(s, "starts")).unionByName(zero(t, "spans"))
    return rows.groupBy(*KEY).agg(*(F.sum(c).alias(c) for c in ("points", "starts", "spans")))


def spine(plan: DataFrame) -> DataFrame:
    """Every row and column index of every tile."""
    rows = plan.select("tile_id", F.lit("row").alias("axis"), F.explode(F.sequence(F.lit(0), F.col("cy1") - F.col("cy0"))).alias("idx"))
    return rows.unionByName(plan.select("tile_id", F.lit("col").alias("axis"), F.explode(F.sequence(F.lit(0), F.col("cx1") - F.col("cx0"))).alias("idx")))


def fold(collected: DataFrame, plan: DataFrame, at_round: int, decay: float = 1.0, method: str = "window") -> DataFrame:
    """Marginals at the end of ``at_round`` from the collectors of all rounds so far.

    Points fade by ``decay`` a round.  ``window`` is one running sum an axis;
    ``naive`` sums every prefix anew.
    """
    new = (F.col("rnd") == at_round).cast("long")
    fade = F.pow(F.lit(float(decay)), (F.lit(at_round) - F.col("rnd")).cast("double"))
    now = collected.where(F.col("rnd") <= at_round).groupBy("tile_id", "axis", "idx").agg(
        F.sum(F.col("points") * fade).alias("n"),
        F.sum("starts").alias("q"),
        F.sum((F.col("points") + F.col("starts")) * new).alias("r"),
        F.sum("spans").alias("span_q"),
        F.sum(F.col("spans") * new).alias("span_q_new"),
    )
    dense = spine(plan).join(now, ["tile_id", "axis", "idx"], "left").fillna(0, ["n", "q", "r", "span_q", "span_q_new"])
    if method == "window":
        run = Window.partitionBy("tile_id", "axis").orderBy("idx").rowsBetween(Window.unboundedPreceding, 0)
        return dense.withColumns({c: F.sum(c).over(run) for c in ("n", "q", "r")})
    upto = dense.select("tile_id", "axis", F.col("idx").alias("j"), "n", "q", "r")
    sums = dense.select("tile_id", "axis", "idx", "span_q", "span_q_new").join(upto, ["tile_id", "axis"]).where("j <= idx")
    return sums.groupBy("tile_id", "axis", "idx", "span_q", "span_q_new").agg(*(F.sum(c).alias(c) for c in ("n", "q", "r"))).select("tile_id", "axis", "idx", "n", "q", "r", "span_q", "span_q_new")


def fold_round(previous: DataFrame | None, collected: DataFrame, plan: DataFrame, decay: float = 1.0) -> DataFrame:
    """One round's step: the marginals before it and its collectors give the marginals after it.

    Only the round's own counters and the tiles' rows and columns are read.
    ``fresh`` are the round's points alone; a column ``work`` of the collectors
    is summed along like them.
    """
    extra = [c for c in ("work",) if c in collected.columns]
    more = lambda form: "".join(", " + form.format(c) for c in extra)
    text = f"""
        WITH objects AS (
          SELECT tile_id, axis, idx, points, starts, spans, 0D AS n0, 0L AS q0, 0L AS g0{more("{}")} FROM {{collected}}
          UNION ALL SELECT tile_id, 'row', explode(sequence(0, cy1 - cy0)), 0L, 0L, 0L, 0D, 0L, 0L{more("0L")} FROM {{plan}}
          UNION ALL SELECT tile_id, 'col', explode(sequence(0, cx1 - cx0)), 0L, 0L, 0L, 0D, 0L, 0L{more("0L")} FROM {{plan}}
          {"UNION ALL SELECT tile_id, axis, idx, 0L, 0L, 0L, n, q, span_q" + more("0L") + " FROM {previous}" if previous is not None else ""}),
        dealt AS (SELECT /*+ REPARTITION(tile_id, axis) */ * FROM objects),
        sums AS (
          SELECT tile_id, axis, idx, sum(points) AS points, sum(starts) AS starts, sum(spans) AS spans, sum(n0) AS n0, sum(q0) AS q0, sum(g0) AS g0{more("sum({0}) AS {0}")}
          FROM dealt GROUP BY tile_id, axis, idx)
        SELECT tile_id, axis, idx, n0 * {decay!r}D + sum(points) OVER upto AS n, q0 + sum(starts) OVER upto AS q, sum(points + starts) OVER upto AS r,
          g0 + spans AS span_q, spans AS span_q_new, sum(points) OVER upto AS fresh{more("sum({0}) OVER upto AS {0}")}
        FROM sums WINDOW upto AS (PARTITION BY tile_id, axis ORDER BY idx ROWS UNBOUNDED PRECEDING)"""
    held = {"previous": previous} if previous is not None else {}
    return collected.sparkSession.sql(text, collected=collected, plan=plan, **held)  # one text, so that a round is analysed once


def counted_collectors(cells: DataFrame, rects: DataFrame, side: DataFrame, on: list[str], values: list[str]) -> DataFrame:
    """Collector rows from counts: ``values`` by (cx, cy) and ``queries`` by rectangle, at their tiles' rows and columns.

    ``side`` is a plan's probe side, joined by bounds and by the columns ``on``.
    """
    same = "".join(f" AND o.{c} = t.{c}" for c in on)
    names = ", ".join(values)
    kinds = dict(cells.dtypes)
    zeros = ", ".join(f"CAST(0 AS {kinds[c]}) AS {c}" for c in values)
    part = lambda axis, c: f"named_struct('axis', '{axis}', 'a', greatest(o.{c}0, t.t_{c}0) - t.t_{c}0, 'b', least(o.{c}1, t.t_{c}1) - t.t_{c}0)"
    text = f"""
        SELECT tile_id, a.axis, a.idx, {names}, 0L AS starts, 0L AS spans FROM (
          SELECT /*+ BROADCAST(t) */ t.tile_id, {names}, explode(array(named_struct('axis', 'row', 'idx', o.cy - t.t_cy0), named_struct('axis', 'col', 'idx', o.cx - t.t_cx0))) AS a
          FROM {{cells}} o JOIN {{side}} t ON o.cx BETWEEN t.t_cx0 AND t.t_cx1 AND o.cy BETWEEN t.t_cy0 AND t.t_cy1{same})
        UNION ALL
        SELECT tile_id, s.axis, idx, {zeros}, if(idx = s.a, queries, 0L), if(idx = s.a, 0L, queries) FROM (
          SELECT tile_id, queries, s, explode(sequence(s.a, s.b)) AS idx FROM (
            SELECT /*+ BROADCAST(t) */ t.tile_id, o.queries, explode(array({part("row", "cy")}, {part("col", "cx")})) AS s
            FROM {{rects}} o JOIN {{side}} t ON o.cx0 <= t.t_cx1 AND o.cx1 >= t.t_cx0 AND o.cy0 <= t.t_cy1 AND o.cy1 >= t.t_cy0{same}))"""
    return cells.sparkSession.sql(text, cells=cells, rects=rects, side=side)


def expire(points: DataFrame, at_round: int, window: int) -> DataFrame:
    """Points still held at the end of a round: those of the last ``window`` rounds."""
    return points.where((F.col("rnd") <= at_round) & (F.col("rnd") > at_round - window))


def tile_totals(marginals: DataFrame, axis: str = "row") -> DataFrame:
    """Whole-tile n, q and r: the last index of either axis."""
    last = F.max_by(F.struct("n", "q", "r"), "idx").alias("t")
    return marginals.where(F.col("axis") == axis).groupBy("tile_id").agg(last).select("tile_id", "t.*")


def subtile_stats(marginals: DataFrame) -> DataFrame:
    """Both parts' n, q and r for every line behind which a tile can be cut."""
    run = Window.partitionBy("tile_id", "axis").orderBy("idx")
    whole = Window.partitionBy("tile_id", "axis")
    rows = marginals.withColumns({
        "next_span": F.lead("span_q").over(run), "next_new": F.lead("span_q_new").over(run),
        **{f"{c}_all": F.max(c).over(whole) for c in ("n", "q", "r")},
    })
    return rows.where("next_span is not null").select(
        "tile_id", "axis", "idx", F.col("n").alias("n1"), F.col("q").alias("q1"), F.col("r").alias("r1"),
        (F.col("n_all") - F.col("n")).alias("n2"), (F.col("q_all") - F.col("q") + F.col("next_span")).alias("q2"), (F.col("r_all") - F.col("r") + F.col("next_new")).alias("r2"),
    )


def classify_queries(clipped: DataFrame) -> DataFrame:
    """For each row of a tile: queries that only start, only end, do both or pass through."""
    each = clipped.withColumn("idx", F.explode(F.sequence("row0", "row1")))
    starts, ends = F.col("idx") == F.col("row0"), F.col("idx") == F.col("row1")
    one = lambda c: F.sum(c.cast("long"))
    return each.groupBy("tile_id", "idx").agg(
        one(starts & ~ends).alias("start_only"), one(ends & ~starts).alias("end_only"), one(starts & ends).alias("both_ends"), one(~starts & ~ends).alias("pass_through"), F.count("*").alias("total")
    )


def rebuild_marginals(points: DataFrame, queries: DataFrame, plan: DataFrame, tile_ids: list[int], at_round: int, decay: float = 1.0) -> DataFrame:
    """Marginals of new tiles recounted from cell counts; other tiles are not read."""
    from gridtide.operators.routing import route_points, route_queries

    some = plan.where(F.col("tile_id").isin(tile_ids))
    return fold(collectors(in_tile(route_points(points, some), some), clip(route_queries(queries, some), some)), some, at_round, decay)
