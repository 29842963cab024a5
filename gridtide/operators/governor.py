"""The automaton that decides between doing nothing and rebalancing."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LEFT, RIGHT = -2, 2


@dataclass
class Governor:
    """Five stages; more arrivals than before move right, others left.

    At the left end the decision flips and the stage returns to the middle; the
    right end holds.  After ``beta`` rounds without a flip one is forced.
    """

    beta: int = 20
    stage: int = 0
    rebalance: bool = False
    repeats: int = 0
    previous: float | None = None

    def step(self, r_total: float) -> bool:
        """Take the round's arrivals; returns whether to rebalance."""
        if self.previous is not None:
            self.stage = min(RIGHT, self.stage + 1) if r_total > self.previous else self.stage - 1
            if self.repeats >= self.beta:
                self.stage = LEFT
            if self.stage <= LEFT:
                self.stage, self.rebalance, self.repeats = 0, not self.rebalance, 0
        self.repeats += 1
        self.previous = r_total
        return self.rebalance


def govern(rounds: DataFrame, beta: int = 20) -> DataFrame:
    """(rnd, r_total, stage, rebalance, repeats) of a table of rounds, as one fold.

    The fold reads the rounds in order in one row: as many as were played, not
    as many as there are objects.
    """
    steps = F.array_sort(F.collect_list(F.struct("rnd", F.col("r_total").cast("double").alias("r_total"))))
    state = "struct<stage:int,rebalance:boolean,repeats:int,previous:double,log:array<struct<rnd:int,r_total:double,stage:int,rebalance:boolean,repeats:int>>>"
    start = F.lit(None).cast("double")
    zero = F.struct(F.lit(0).alias("stage"), F.lit(False).alias("rebalance"), F.lit(0).alias("repeats"), start.alias("previous"), F.expr("cast(array() as array<struct<rnd:int,r_total:double,stage:int,rebalance:boolean,repeats:int>>)").alias("log")).cast(state)

    def move(s, x):
        first = s["previous"].isNull()
        stepped = F.when(x["r_total"] > s["previous"], F.least(F.lit(RIGHT), s["stage"] + 1)).otherwise(s["stage"] - 1)
        forced = F.when(s["repeats"] >= beta, F.lit(LEFT)).otherwise(stepped)
        flip = ~first & (forced <= LEFT)
        stage = F.when(first, F.lit(0)).when(flip, F.lit(0)).otherwise(forced).cast("int")
        rebalance = F.when(flip, ~s["rebalance"]).otherwise(s["rebalance"])
        repeats = (F.when(flip, F.lit(0)).otherwise(s["repeats"]) + 1).cast("int")
        entry = F.struct(x["rnd"].alias("rnd"), x["r_total"].alias("r_total"), stage.alias("stage"), rebalance.alias("rebalance"), repeats.alias("repeats"))
        return F.struct(stage.alias("stage"), rebalance.alias("rebalance"), repeats.alias("repeats"), x["r_total"].alias("previous"), F.concat(s["log"], F.array(entry)).alias("log")).cast(state)

    return rounds.agg(F.aggregate(steps, zero, move)["log"].alias("log")).select(F.inline("log"))
