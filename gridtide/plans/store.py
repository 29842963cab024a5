"""Versioned plans: each round's plan is written once and read by whoever is pinned to it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridtide.plans.layout import Tile, plan_frame
from gridtide.schemas import PLAN


class PlanStore:
    """Plans under ``path/round=N``; publishing a round again replaces it, so replays are harmless."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def publish(self, at_round: int, tiles: list[Tile]) -> None:
        frame = plan_frame(self.spark, tiles, at_round).drop("round").coalesce(1)
        frame.write.mode("overwrite").parquet(f"{self.path}/round={at_round}")

    def history(self) -> DataFrame:
        names = [f.split()[0] for f in PLAN.split(", ")]
        return self.spark.read.schema(PLAN.split(", ", 1)[1]).option("basePath", self.path).parquet(f"{self.path}/round=*").select(*names)

    def read(self, at_round: int) -> list[Tile]:
        """The plan of a round, or of the latest one before it."""
        rows = self.history().where(F.col("round") <= at_round)
        latest = rows.agg(F.max("round")).first()[0]
        got = rows.where(F.col("round") == latest).orderBy("tile_id").collect()  # a row for each tile
        return [Tile(r.tile_id, r.machine_id, r.cx0, r.cy0, r.cx1, r.cy1, tuple(r.parent_ids or ()), r.prev_machine_id, r.born_round, r.retired_round) for r in got]

    def latest(self) -> int | None:
        try:
            return self.history().agg(F.max("round")).first()[0]
        except Exception as error:
            if "PATH_NOT_FOUND" in str(error):
                return None
            raise


class PointStore:
    """Points under the round and tile of their arrival; appended to, never rewritten when tiles move."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def append(self, routed: DataFrame) -> None:
        """Add routed points; rounds that are written again replace themselves."""
        out = routed.repartition("rnd", "tile_id").write.partitionBy("rnd", "tile_id").mode("overwrite")
        out.option("partitionOverwriteMode", "dynamic").parquet(self.path)

    def read(self, from_round: int | None = None, to_round: int | None = None) -> DataFrame:
        """Stored points; round and tile filters prune folders."""
        held = self.spark.read.parquet(self.path)
        if from_round is not None:
            held = held.where(F.col("rnd") >= from_round)
        return held if to_round is None else held.where(F.col("rnd") <= to_round)
