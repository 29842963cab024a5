"""What users of the subscriptions ask: matches by region, hot cells, queries without matches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.plans.layout import small
from gridtide.sources.tables import table


def matches_by_region(spark: SparkSession, sf_dir: str, matches: DataFrame, queries: DataFrame) -> DataFrame:
    """Matches and subscribers by region and nation of the subscriber; users map onto customers by modulo."""
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nations = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    size = customers.count()
    per = matches.groupBy("query_id").agg(F.count("*").alias("m")).join(queries.select("query_id", "subscriber_id"), "query_id")
    per = per.withColumn("c_custkey", F.pmod(F.col("subscriber_id"), F.lit(size)) + 1)
    full = per.join(customers, "c_custkey").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
    return full.groupBy("r_name", "n_name").agg(F.sum("m").alias("matches"), F.count_distinct("subscriber_id").alias("subscribers"))


def hot_cells(points: DataFrame, k: int = 10) -> DataFrame:
    """The ``k`` cells with most points, ties by place."""
    return points.groupBy("cx", "cy").agg(F.count("*").alias("points")).orderBy(F.desc("points"), "cx", "cy").limit(k)


def unmatched_queries(queries: DataFrame, matches: DataFrame) -> DataFrame:
    return queries.join(matches, "query_id", "left_anti").select("query_id", "rnd")


def match_rate(matches: DataFrame, points: DataFrame) -> DataFrame:
    """Matches and matched points by tag."""
    full = points.join(matches.groupBy("point_id").agg(F.count("*").alias("m")), "point_id", "left").fillna(0, ["m"])
    return full.groupBy("tag").agg(F.count("*").alias("points"), F.sum((F.col("m") > 0).cast("long")).alias("matched"), F.sum("m").alias("matches"))


def heat_map(points: DataFrame, hours: int = 6, coarse: int = 8) -> DataFrame:
    """Points by coarse cell, one column for each part of the day."""
    parts = list(range(24 // hours))
    part = F.floor(F.hour("ts") / hours).cast("int")
    rows = points.select(F.expr(f"int(cx div {coarse})").alias("hx"), F.expr(f"int(cy div {coarse})").alias("hy"), part.alias("part"))
    out = rows.groupBy("hx", "hy").pivot("part", parts).count().fillna(0)
    return out.withColumnsRenamed({str(p): f"part_{p}" for p in parts})


def keyword_subscriptions(documents: DataFrame, subscriptions: DataFrame) -> DataFrame:
    """Documents inside a subscription's cell rectangle that hold its keyword (subscriptions: a bounded table)."""
    on = F.col("cx").between(F.col("cx0"), F.col("cx1")) & F.col("cy").between(F.col("cy0"), F.col("cy1")) & F.contains(F.col("text"), F.col("keyword"))
    return documents.join(small(subscriptions), on).select("query_id", F.col("point_id").alias("doc_id"), "tag")
