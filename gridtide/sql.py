"""The engine's tables as temporary views, and its relational methods as Spark SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gridtide.config import EVENTS, MACHINES
from gridtide.plans.layout import Tile, even_layout, plan_frame
from gridtide.sources import tables

METHODS = {
    "route_points": """
        SELECT /*+ BROADCAST(t) */ p.point_id, t.tile_id, t.machine_id FROM points p
        JOIN plan t ON p.cx BETWEEN t.cx0 AND t.cx1 AND p.cy BETWEEN t.cy0 AND t.cy1""",
    "route_queries": """
        SELECT /*+ BROADCAST(t) */ q.query_id, t.tile_id, t.machine_id FROM queries q
        JOIN plan t ON q.cx0 <= t.cx1 AND q.cx1 >= t.cx0 AND q.cy0 <= t.cy1 AND q.cy1 >= t.cy0""",
    "tile_costs": """
        WITH p AS (SELECT /*+ BROADCAST(t) */ t.tile_id, count(*) AS n FROM points p
                   JOIN plan t ON p.cx BETWEEN t.cx0 AND t.cx1 AND p.cy BETWEEN t.cy0 AND t.cy1 GROUP BY 1),
             q AS (SELECT /*+ BROADCAST(t) */ t.tile_id, count(*) AS q FROM queries q
                   JOIN plan t ON q.cx0 <= t.cx1 AND q.cx1 >= t.cx0 AND q.cy0 <= t.cy1 AND q.cy1 >= t.cy0 GROUP BY 1)
        SELECT t.tile_id, t.machine_id, coalesce(n, 0) AS n, coalesce(q, 0) AS q,
               CAST(coalesce(n, 0) AS DOUBLE) * coalesce(q, 0) * (coalesce(n, 0) + coalesce(q, 0)) AS numerator
        FROM plan t LEFT JOIN p USING (tile_id) LEFT JOIN q USING (tile_id)""",
    "matches": """
        WITH qc AS (SELECT *, explode(sequence(cx0, cx1)) AS qx FROM queries),
             qd AS (SELECT *, explode(sequence(cy0, cy1)) AS qy FROM qc)
        SELECT q.query_id, p.point_id FROM points p JOIN qd q ON p.cx = q.qx AND p.cy = q.qy
        WHERE p.x BETWEEN q.x0 AND q.x1 AND p.y BETWEEN q.y0 AND q.y1 AND q.qts <= p.ts""",
    "marginals": """
        WITH l AS (SELECT /*+ BROADCAST(t) */ t.tile_id, p.cy - t.cy0 AS row, p.cx - t.cx0 AS col FROM points p
                   JOIN plan t ON p.cx BETWEEN t.cx0 AND t.cx1 AND p.cy BETWEEN t.cy0 AND t.cy1),
             c AS (SELECT tile_id, 'row' AS axis, row AS idx, count(*) AS n FROM l GROUP BY 1, 3
                   UNION ALL SELECT tile_id, 'col', col, count(*) FROM l GROUP BY 1, 3)
        SELECT tile_id, axis, idx, sum(n) OVER (PARTITION BY tile_id, axis ORDER BY idx) AS n FROM c""",
}


def register_views(spark: SparkSession, sf_dir: str, tiles: list[Tile] | None = None) -> None:
    """Create the views ``points``, ``queries`` and ``plan``."""
    tables.event_points(spark, sf_dir).createOrReplaceTempView("points")
    tables.event_queries(spark, sf_dir).createOrReplaceTempView("queries")
    plan_frame(spark, tiles or even_layout(EVENTS, MACHINES)).createOrReplaceTempView("plan")


def run(spark: SparkSession, method: str) -> DataFrame:
    return spark.sql(METHODS[method])


def explain(frame: DataFrame) -> str:
    """The formatted physical plan as text."""
    return frame._jdf.queryExecution().explainString(frame.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
