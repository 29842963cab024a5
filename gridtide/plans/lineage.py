"""Which earlier tiles still hold data of a tile: the chain back over moves, splits and merges."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.plans.layout import Tile

LINK = "current_tile long, stored_tile long, machine_id int, born_round int, retired_round int, t_cx0 int, t_cy0 int, t_cx1 int, t_cy1 int, depth int"


def tile_history(plans: list[list[Tile]]) -> list[Tile]:
    """All tiles of successive plans (plan ``i`` in force in round ``i``), with the round in which each retired."""
    seen: dict[int, Tile] = {}
    for rnd, tiles in enumerate(plans):
        live = {t.tile_id for t in tiles}
        for t in tiles:
            seen.setdefault(t.tile_id, replace(t, born_round=rnd))
        for ident, t in seen.items():
            if ident not in live and t.retired_round is None:
                seen[ident] = replace(t, retired_round=rnd)
    return sorted(seen.values(), key=lambda t: t.tile_id)


def resolve_chain(history: list[Tile], tile_id: int, oldest_round: int) -> list[tuple[Tile, int]]:
    """(tile, depth) from a tile back to the ancestors that were in force at or after ``oldest_round``."""
    by_id = {t.tile_id: t for t in history}
    out, level, depth = [], [tile_id], 0
    while level:
        live = [by_id[i] for i in level if by_id[i].retired_round is None or by_id[i].retired_round > oldest_round]
        out += [(t, depth) for t in live]
        level, depth = sorted({p for t in live if t.born_round > oldest_round for p in t.parent_ids}), depth + 1
    return out


def chain_frame(spark: SparkSession, history: list[Tile], oldest_round: int) -> DataFrame:
    """The chains of all live tiles; each link asks for the current tile's own rectangle only."""
    rows = []
    for t in history:
        if t.retired_round is None:
            rows += [(t.tile_id, a.tile_id, a.machine_id, a.born_round, a.retired_round, t.cx0, t.cy0, t.cx1, t.cy1, d) for a, d in resolve_chain(history, t.tile_id, oldest_round)]
    return spark.createDataFrame(rows, LINK)


def chain_sql(spark: SparkSession, history: DataFrame, oldest_round: int) -> DataFrame:
    """The same chains by a recursive query over a history table (tile_id, parent_ids, born_round, retired_round)."""
    history.createOrReplaceTempView("tile_history")
    return spark.sql(f"""
        WITH RECURSIVE links(current_tile, stored_tile, depth) AS (
          SELECT tile_id, tile_id, 0 FROM tile_history WHERE retired_round IS NULL
          UNION ALL
          SELECT l.current_tile, p.parent, l.depth + 1
          FROM links l JOIN (SELECT tile_id, explode(parent_ids) AS parent, born_round FROM tile_history) p
            ON p.tile_id = l.stored_tile AND p.born_round > {oldest_round}
        )
        SELECT l.current_tile, l.stored_tile, l.depth, h.machine_id, h.born_round, h.retired_round
        FROM links l JOIN tile_history h ON h.tile_id = l.stored_tile
        WHERE h.retired_round IS NULL OR h.retired_round > {oldest_round}
    """)


def prune(history: list[Tile], oldest_round: int) -> list[Tile]:
    """Forget tiles whose data have expired and cut the links to them."""
    kept = [t for t in history if t.retired_round is None or t.retired_round > oldest_round]
    ids = {t.tile_id for t in kept}
    return [replace(t, parent_ids=tuple(p for p in t.parent_ids if p in ids)) for t in kept]


def retire_ready(history: DataFrame, oldest_round: int, at_round: int) -> DataFrame:
    """Retired tiles whose data have expired and after whose retirement a round has begun."""
    return history.where(F.col("retired_round").isNotNull() & (F.col("retired_round") <= oldest_round) & (F.col("retired_round") < at_round))


def chain_ledger(answers: DataFrame) -> DataFrame:
    """(query_id, links, rows): rows sent by each link and their sum, the query's final answer size."""
    by_link = answers.groupBy("query_id", "stored_tile").agg(F.count("*").alias("sent"))
    return by_link.groupBy("query_id").agg(F.count("*").alias("links"), F.sum("sent").alias("rows"))


def acknowledge(links: DataFrame, answers: DataFrame) -> DataFrame:
    """(query_id, expected, acknowledged, rows, final): each asked link acknowledges with the rows it sent; final once all have.

    ``links``: (query_id, stored_tile, ...) as asked; ``answers``: result rows as
    received, with their link.  A link without any row acknowledges as well; an
    answer of a link that was not asked leaves the query unfinished.
    """
    asked = links.select("query_id", "stored_tile").distinct()
    got = answers.groupBy("query_id", "stored_tile").agg(F.count("*").alias("sent"))
    both = asked.withColumn("asked", F.lit(1)).join(got, ["query_id", "stored_tile"], "full")
    sums = both.groupBy("query_id").agg(F.count("asked").alias("expected"), F.count("*").alias("acknowledged"), F.coalesce(F.sum("sent"), F.lit(0)).alias("rows"))
    return sums.withColumn("final", F.col("expected") == F.col("acknowledged"))


def chain_stats(chain: DataFrame) -> DataFrame:
    """Chains, mean and largest number of links."""
    per = chain.groupBy("current_tile").agg(F.count("*").alias("links"))
    return per.agg(F.count("*").alias("chains"), F.avg("links").alias("mean_links"), F.max("links").alias("most_links"))
