"""Connected components of a link table, by repeated star contraction.

Each pass hangs the larger neighbours of a node on its smallest neighbour
(large star) and then the smaller ones on the smallest (small star), until
every node points at the least id it can reach.  Links stay distributed; the
driver only sees one changed-or-not flag a pass.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import Scratch


def _stars(links: DataFrame, scratch: Scratch, tag: str) -> DataFrame:
    """One large-star and one small-star pass over (u, v) with u > v."""
    both = links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    low = scratch.keep(low, f"{tag}-low")  # written, so that the join of a node with very many links can be split
    large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v")
    large = large.unionByName(low.where("m < u").select("u", F.col("m").alias("v"))).distinct()
    least = large.groupBy("u").agg(F.min("v").alias("m"))
    small = large.join(least, "u").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return small.unionByName(least.select("u", F.col("m").alias("v"))).distinct()


def connected(links: DataFrame, scratch: Scratch, tag: str) -> DataFrame:
    """(node, root) for every node of ``links`` (u, v); root is the least id reachable.

    Self links and repeats are ignored; a null end drops the link.  An empty
    link table gives no rows.
    """
    now = scratch.keep(
        links.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(),
        f"{tag}-0",
    )
    turn = 0
    while True:
        turn += 1
        now = scratch.keep(_stars(now, scratch, tag), f"{tag}-{turn}")
        scratch.drop(f"{tag}-{turn - 1}")
        # settled when each node has one link and no root has a link of its own
        seen = now.agg(F.count("*"), F.count_distinct("u")).first()
        if seen[0] == seen[1] and now.join(now.select(F.col("u").alias("v")), "v", "left_semi").isEmpty():
            break
    scratch.drop(f"{tag}-low")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(
        now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )
