"""Temperature mixing of sources to target weights, in DataFrame functions only.

A source's share of all tokens is raised to an exponent and normalised.  The
exponent is bisected so that the weights reach a target entropy, and again so
that no source is repeated more often than a limit; the larger exponent (the
flatter mixture gives way) holds.  A source's budget is spent in whole passes
over its documents and one partial pass.  Documents lie in hashed blocks of a
bounded size; the partial pass takes whole blocks in a permuted order and, of
the block at the edge, documents in a permuted order.

Which copies a document has follows from its source's numbers and its own id
alone: the first block that the partial pass doesn't take whole, and in that block
the last document that it takes.  So texts are never shuffled.

Defined cases: a null source is the empty name; null and blank texts have no
tokens and follow their block; sources without any token get weight 0 and one
pass; one source has weight 1; rows that repeat an id share their fate; a text of
any length counts whole; further columns stay as they are, and a column that is
added under a name that is taken gets underscores before it; an empty table gives
no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .store import Scratch, bounded, free_name

BLOCK_DOCS = 4096  # documents of a block on average
LEVELS, PASSES = 5, 6  # bisection levels evaluated at once, and how often
SEED = 17
SOURCES_MOST = 1 << 17  # sources whose numbers are broadcast at most


def token_count(text):
    """Words ``[^\\x20\\x09-\\x0D]+`` of a text."""
    return F.coalesce(F.regexp_count(text, F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long")


class TemperatureMixer:
    """Weights, budgets and copies of a mixture.

    ``flatness`` places the target entropy between that of the natural shares
    (0) and that of equal shares (1); ``repeats`` is the most passes over a
    source; ``budget`` is the mixture's size in multiples of all tokens.
    """

    def __init__(self, spark: SparkSession, flatness: float = 0.5, repeats: float = 4.0, budget: float = 1.0, scratch: Scratch | None = None):
        self.spark, self.flatness, self.repeats, self.budget = spark, flatness, repeats, budget
        self.scratch = scratch or Scratch(spark, "mixing")

    def _measures(self, shares: DataFrame, exponents: list[float]) -> dict[float, tuple[float, float]]:
        """(entropy, most passes over a source) at each exponent: one row for each comes to the driver."""
        grid = F.explode(F.array(*(F.lit(float(a)) for a in exponents))).alias("a")
        raised = shares.select("p", grid).select("a", F.pow("p", F.col("a")).alias("x"), F.log("p").alias("l"), (F.pow("p", F.col("a")) / F.col("p")).alias("r"))
        sums = raised.groupBy("a").agg(F.sum("x").alias("z"), F.sum(F.col("x") * F.col("l")).alias("xl"), F.max("r").alias("r"))
        return {row.a: (math.log(row.z) - row.a * row.xl / row.z, self.budget * row.r / row.z) for row in sums.collect()}

    def _bisect(self, shares: DataFrame, enough) -> float:
        """Least exponent in [0, 1] from which ``enough(entropy, passes)`` holds; 1 if it never does."""
        low, high = 0.0, 1.0
        if enough(*self._measures(shares, [0.0])[0.0]):
            return 0.0
        for _ in range(PASSES):  # each evaluates all midpoints of LEVELS bisections
            n = 1 << LEVELS
            points = [low + (high - low) * i / n for i in range(1, n)]
            got = self._measures(shares, points)
            left, right = 0, n
            while right - left > 1:
                middle = (left + right) // 2
                left, right = (left, middle) if enough(*got[points[middle - 1]]) else (middle, right)
            low, high = low + (high - low) * left / n, low + (high - low) * right / n
        return high

    def plan(self, documents: DataFrame) -> tuple[DataFrame, DataFrame, float]:
        """(sources, blocks, exponent): weights and passes by source, and which blocks the partial pass takes."""
        slim = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("source"), token_count(F.col("text").cast("string")).alias("tokens"))
        slim = self.scratch.keep(slim, "slim")
        sources = self.scratch.keep(slim.groupBy("source").agg(F.count("*").alias("docs"), F.sum("tokens").alias("all_tokens")), "sources")
        total = sources.agg(F.sum("all_tokens")).first()[0] or 0
        some = sources.where("all_tokens > 0").withColumn("p", F.col("all_tokens") / F.lit(float(max(1, total))))
        exponent = 1.0
        if total:
            natural, equal = self._measures(some, [1.0])[1.0][0], math.log(some.count())
            target = natural + self.flatness * (equal - natural)
            exponent = max(self._bisect(some, lambda h, _: h <= target + 1e-12), self._bisect(some, lambda _, r: r <= self.repeats + 1e-12))
        raised = F.when(F.col("all_tokens") > 0, F.pow(F.col("all_tokens") / F.lit(float(max(1, total))), F.lit(exponent))).otherwise(0.0)
        norm = sources.select(F.sum(raised)).first()[0] or 1.0
        share = F.when(F.col("all_tokens") > 0, F.floor(F.col("weight") * F.lit(self.budget * total)).cast("long")).otherwise(0)
        sources = sources.withColumn("weight", raised / F.lit(norm)).withColumn("spend", share)
        whole = F.when(F.col("all_tokens") > 0, F.floor(F.col("spend") / F.col("all_tokens"))).otherwise(1).cast("long")
        sources = sources.withColumn("passes", whole).withColumn("rest", F.col("spend") - F.when(F.col("all_tokens") > 0, F.col("passes") * F.col("all_tokens")).otherwise(0))
        sources = self.scratch.keep(sources.withColumn("n_blocks", F.ceil(F.col("docs") / BLOCK_DOCS).cast("int")), "weights")
        placed = slim.join(sources.select("source", "n_blocks", "passes", "rest"), "source").withColumn("block", block_of())
        sums = placed.groupBy("source", "block", "passes", "rest").agg(F.sum("tokens").alias("block_tokens"))
        order = Window.partitionBy("source").orderBy("block_key", "block")
        sums = sums.withColumn("block_key", F.xxhash64("source", "block", "passes", F.lit(SEED)))
        before = sums.withColumn("before", F.sum("block_tokens").over(order.rowsBetween(Window.unboundedPreceding, -1))).fillna(0, ["before"])
        before = before.withColumn("rank", F.row_number().over(order)).withColumn("left", F.col("rest") - F.col("before"))
        blocks = self.scratch.keep(before, "blocks")
        # the blocks before ``stop`` are taken whole; of that block, documents in order while they fit
        stop = F.struct("block_key", "block", "left", "block_tokens")
        stops = blocks.where("left <= 0 or left < block_tokens").groupBy("source").agg(F.min(stop).alias("stop"))
        edge = stops.where("stop.left > 0").select("source", "stop.block", "stop.left")
        inside = placed.join(edge, ["source", "block"]).withColumn("key", doc_key())
        run = Window.partitionBy("source", "block").orderBy("key", "doc_id").rangeBetween(Window.unboundedPreceding, 0)
        taken = inside.withColumn("upto", F.sum("tokens").over(run)).where(F.col("upto") <= F.col("left"))
        cuts = taken.groupBy("source").agg(F.max(F.struct("key", "doc_id")).alias("cut"))
        sources = sources.join(stops, "source", "left").join(cuts, "source", "left")
        sources = sources.select("source", "docs", "all_tokens", "weight", "spend", "passes", "rest", "n_blocks", "stop.block_key", "stop.block", F.col("cut.key").alias("cut_key"), F.col("cut.doc_id").alias("cut_id"))
        return self.scratch.keep(sources, "plan"), blocks, exponent

    def assign(self, documents: DataFrame, ranks: bool = False) -> DataFrame:
        """``documents`` with a struct ``_mix``: weight, copies, passes, block, and with ``ranks`` the block's place in the partial pass."""
        sources, blocks, _ = self.plan(documents)
        row, plan, mix = (free_name(documents.columns, n) for n in ("mix_row", "mix_plan", "_mix"))
        packed = documents.select(F.struct(*(F.col(f"`{c}`") for c in documents.columns)).alias(row))
        name, ident = F.coalesce(F.col(f"{row}.source").cast("string"), F.lit("")), F.col(f"{row}.doc_id").cast("long")
        by_source = sources.select(F.struct("*").alias(plan))
        keys = packed.join(bounded(by_source, SOURCES_MOST), F.col(f"{plan}.source") == name)
        part = lambda c: F.col(f"{plan}.{c}")
        block = block_of(ident, part("n_blocks"))
        block_key = F.xxhash64(part("source"), block, part("passes"), F.lit(SEED))
        key, least = doc_key(ident, part("passes")), F.lit(-(2**63))
        whole = part("block_key").isNull() | (block_key < part("block_key")) | ((block_key == part("block_key")) & (block < part("block")))
        at_edge = (block == part("block")) & ((key < part("cut_key")) | ((key == part("cut_key")) & (F.coalesce(ident, least) <= F.coalesce(part("cut_id"), least))))
        extra = F.when((part("all_tokens") > 0) & (part("rest") > 0) & (whole | F.coalesce(at_edge, F.lit(False))), 1).otherwise(0)
        fields = [part("weight").alias("weight"), (part("passes") + extra).alias("copies"), part("passes").alias("passes"), block.alias("block")]
        if ranks:
            b = blocks.select(F.struct("source", "block", "rank").alias("mix_rank"))
            keys = keys.join(b, (F.col("mix_rank.source") == part("source")) & (F.col("mix_rank.block") == block))
            fields.append(F.col("mix_rank.rank").alias("rank"))
        return keys.select(*(F.col(f"{row}.`{c}`").alias(c) for c in documents.columns), F.struct(*fields).alias(mix))

    def mix(self, documents: DataFrame) -> DataFrame:
        """The mixture: each document as often as it has copies, with its pass and place in the permuted order."""
        rows = self.assign(documents)
        held = rows.columns[-1]
        turn = free_name(documents.columns, "mix_pass")
        spot, order = (free_name([*documents.columns, turn], n) for n in ("mix_block", "mix_key"))
        rows = rows.where(F.col(f"{held}.copies") > 0).withColumn(turn, F.explode(F.sequence(F.lit(1).cast("long"), F.col(f"{held}.copies"))))
        place = F.xxhash64(F.coalesce(F.col("source").cast("string"), F.lit("")), F.col(f"{held}.block"), turn, F.lit(SEED))
        return rows.withColumn(spot, place).withColumn(order, doc_key("doc_id", F.col(turn))).drop(held)


def _id(doc_id):
    return (F.col(doc_id) if isinstance(doc_id, str) else doc_id).cast("long")


def block_of(doc_id="doc_id", n_blocks=None):
    return F.pmod(F.xxhash64(_id(doc_id), F.lit(SEED + 1)), F.col("n_blocks") if n_blocks is None else n_blocks).cast("int")


def doc_key(doc_id="doc_id", passes=None):
    return F.xxhash64(_id(doc_id), F.col("passes") if passes is None else passes, F.lit(SEED + 2))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies of every document in the mixture of all sources."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = TemperatureMixer(spark).assign(docs.select("doc_id", "source", "text"), ranks=True)
    return rows.select("doc_id", "source", F.col("_mix.weight").alias("weight"), F.col("_mix.copies").alias("copies"), F.col("_mix.block").alias("block"), F.col("_mix.rank").alias("block_rank"))
