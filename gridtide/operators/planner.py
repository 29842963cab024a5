"""Reducing a machine's load: choice of tiles, choice of a cut, one rebalance.

Everything here works on one donor's tiles: the costs of its tiles and, for a
cut, one tile's marginals.  These reach the driver by filtered, bounded reads.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridtide.operators.marginals import subtile_stats
from gridtide.plans.layout import Tile, move_tiles, split_tile


@dataclass
class AxisStats:
    """Marginals of one axis as arrays."""

    n: np.ndarray
    q: np.ndarray
    r: np.ndarray
    span_q: np.ndarray
    span_q_new: np.ndarray

    def parts(self, after: int) -> tuple[float, float]:
        """Cost numerators of the first and the second part of a cut."""
        first = float(self.n[after]) * float(self.q[after]) * float(self.r[after])
        n2 = float(self.n[-1] - self.n[after])
        q2 = float(self.q[-1] - self.q[after] + self.span_q[after + 1])
        r2 = float(self.r[-1] - self.r[after] + self.span_q_new[after + 1])
        return first, n2 * q2 * r2


@dataclass(frozen=True)
class Cut:
    gap: float
    axis: str
    moved: str
    after: int
    probes: int = 0


def greedy_subset(costs: list[tuple[int, float]], cap: float, order: str = "cost") -> tuple[list[int], float]:
    """Tiles (id, cost) kept while their sum stays within ``cap``; largest first, or by id."""
    ordered = sorted(costs, key=(lambda t: (-t[1], t[0])) if order == "cost" else (lambda t: t[0]))
    kept, total = [], 0.0
    for ident, cost in ordered:
        if total + cost <= cap:
            kept.append(ident)
            total += cost
            if total == cap:
                break
    return kept, total


def exact_subset(costs: list[tuple[int, float]], cap: float) -> float:
    """Largest subset sum within ``cap``, by trying all subsets (few tiles only)."""
    if len(costs) > 16:
        raise ValueError("too many tiles for an exhaustive search")
    values = [c for _, c in costs]
    return max((s for k in range(len(values) + 1) for p in combinations(values, k) if (s := sum(p)) <= cap), default=0.0)


def _gap(parts: tuple[float, float], moved: str, tile: float, high: float, low: float) -> float:
    """Signed gap donor minus receiver after the ``moved`` part has gone over."""
    kept, gone = (parts[1], parts[0]) if moved == "first" else parts
    return (high - tile + kept) - (low + gone)


def best_split(axes: dict[str, AxisStats], tile: float, high: float, low: float, method: str = "binary") -> Cut | None:
    """The cut that leaves the smallest absolute gap; ties by axis (row first), side, then line.

    As a line advances the first part never gets cheaper and the second never
    dearer, so the gap is monotone and its sign change can be searched for.
    """
    found = []
    probes = 0
    for axis in ("row", "col"):
        stats = axes[axis]
        lines = len(stats.n) - 1
        for moved in ("first", "second"):
            gap = lambda i: _gap(stats.parts(i), moved, tile, high, low)  # noqa: B023, E731
            if lines < 1:
                continue
            if method == "scan":
                probes += lines
                found += [(abs(gap(i)), axis != "row", moved, i) for i in range(lines)]
                continue
            down = moved == "first"  # the gap falls as the line advances

            def leftmost(holds):
                lo, hi = 0, lines
                while lo < hi:
                    mid = (lo + hi) // 2
                    lo, hi = (lo, mid) if holds(mid) else (mid + 1, hi)
                return lo

            turn = leftmost((lambda i: gap(i) <= 0) if down else (lambda i: gap(i) >= 0))  # noqa: B023
            probes += max(1, lines.bit_length())
            for i in {turn, turn - 1} & set(range(lines)):
                value = gap(i)
                same = leftmost((lambda j: gap(j) <= value) if down else (lambda j: gap(j) >= value))  # noqa: B023
                found.append((abs(value), axis != "row", moved, same))
    if not found:
        return None
    size, other, moved, after = min(found)
    return Cut(size, "col" if other else "row", moved, after, probes)


def axis_stats(rows) -> dict[str, AxisStats]:
    """Collected marginals of one tile as arrays by axis."""
    out = {}
    for axis in ("row", "col"):
        own = sorted((r for r in rows if r["axis"] == axis), key=lambda r: r["idx"])
        out[axis] = AxisStats(*(np.array([float(r[c]) for r in own]) for c in ("n", "q", "r", "span_q", "span_q_new")))
    return out


@dataclass(frozen=True)
class Action:
    """What a round did: kind (none, subset, split), machines, tiles and the gap before and after."""

    kind: str
    donor: int | None = None
    receiver: int | None = None
    tiles: tuple[int, ...] = ()
    cut: Cut | None = None
    before: float = 0.0
    after: float = 0.0


def rebalance_once(tiles: list[Tile], load: dict[int, float], costs_of, marginals_of, at_round: int, method: str = "binary", order: str = "cost") -> tuple[list[Tile], Action]:
    """One rebalance: the dearest machine that can gives the cheapest one tiles or a part of a tile.

    ``load`` maps machines to numerators, the reports.  Only then is the donor
    asked for its tiles' costs (``costs_of(machine)``) and, when no subset of
    them will do, for one tile's axes (``marginals_of(tile)``); a donor without
    a feasible move is passed over for the next.
    """
    load = {t.machine_id: load.get(t.machine_id, 0.0) for t in tiles} | load
    receiver = min(load, key=lambda m: (load[m], m))
    for donor in sorted(load, key=lambda m: (-load[m], m)):
        high, low = load[donor], load[receiver]
        if donor == receiver or high <= low:
            continue
        own, costs = [t for t in tiles if t.machine_id == donor], costs_of(donor)
        ids, moved = greedy_subset([(t.tile_id, costs.get(t.tile_id, 0.0)) for t in own], (high - low) / 2, order)
        if moved > 0:
            ids = [i for i in ids if costs.get(i, 0.0) > 0]
            return move_tiles(tiles, set(ids), receiver, at_round), Action("subset", donor, receiver, tuple(ids), None, high - low, high - low - 2 * moved)
        splittable = [t for t in own if t.area > 1]
        if not splittable:
            continue
        t = min(splittable, key=lambda t: (-costs.get(t.tile_id, 0.0), t.tile_id))
        cut = best_split(marginals_of(t), costs.get(t.tile_id, 0.0), high, low, method)
        if cut is not None and cut.gap < high - low:
            return split_tile(tiles, t.tile_id, cut.axis, cut.after, cut.moved, receiver, at_round), Action("split", donor, receiver, (t.tile_id,), cut, high - low, cut.gap)
    return tiles, Action("none")


def pick_pair(report: DataFrame) -> DataFrame:
    """(donor, receiver): the dearest and the cheapest machine, ties by the smaller id."""
    return report.agg(
        F.max_by("machine_id", F.struct("numerator", -F.col("machine_id"))).alias("donor"), F.min_by("machine_id", F.struct("numerator", "machine_id")).alias("receiver")
    )


def greedy_frame(costs: DataFrame, caps: DataFrame, order: str = "cost") -> DataFrame:
    """(machine_id, tile_id, kept) of the greedy choice for many machines at once, as a fold over each one's tiles."""
    first = F.col("numerator") if order == "cost" else F.lit(0.0)
    tiles = costs.groupBy("machine_id").agg(F.array_sort(F.collect_list(F.struct((-first).cast("double").alias("key"), "tile_id", F.col("numerator").cast("double").alias("cost")))).alias("tiles"))
    zero = F.expr("named_struct('total', 0.0D, 'done', false, 'log', cast(array() as array<struct<tile_id:bigint,kept:boolean>>))")

    def step(s, x):
        fits = ~s["done"] & (s["total"] + x["cost"] <= F.col("cap"))
        total = F.when(fits, s["total"] + x["cost"]).otherwise(s["total"])
        log = F.concat(s["log"], F.array(F.struct(x["tile_id"].alias("tile_id"), fits.alias("kept"))))
        return F.struct(total.alias("total"), (s["done"] | (total == F.col("cap"))).alias("done"), log.alias("log"))

    folded = tiles.join(caps, "machine_id").withColumn("f", F.aggregate("tiles", zero, step))
    return folded.select("machine_id", F.inline("f.log"))


def exact_frame(costs: DataFrame, cap: float) -> DataFrame:
    """(best): the largest subset sum within ``cap`` by bit masks, for the few tiles of one machine."""
    ranked = costs.withColumn("bit", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("tile_id")) - 1)
    masks = ranked.agg(F.count("*").alias("k")).select(F.explode(F.sequence(F.lit(0).cast("long"), F.expr("shiftleft(1L, cast(k as int)) - 1"))).alias("mask"))
    bits = masks.join(F.broadcast(ranked), F.expr("shiftright(mask, bit) & 1 = 1"), "left")
    sums = bits.groupBy("mask").agg(F.coalesce(F.sum("numerator"), F.lit(0)).alias("total"))
    return sums.where(F.col("total") <= F.lit(cap)).agg(F.max("total").alias("best"))


def split_scan(marginals: DataFrame, totals: DataFrame) -> DataFrame:
    """All cuts of all tiles with both sides moved: (tile_id, axis, idx, moved, gap).

    ``totals``: (tile_id, cost, high, low) with the tile's, donor's and
    receiver's numerators.
    """
    parts = subtile_stats(marginals).join(F.broadcast(totals), "tile_id")
    c1, c2 = F.col("n1") * F.col("q1") * F.col("r1"), F.col("n2") * F.col("q2") * F.col("r2")
    sides = F.explode(F.array(F.struct(F.lit("first").alias("moved"), c1.alias("gone"), c2.alias("kept")), F.struct(F.lit("second").alias("moved"), c2.alias("gone"), c1.alias("kept")))).alias("s")
    rows = parts.select("tile_id", "axis", "idx", "cost", "high", "low", sides)
    gap = F.abs((F.col("high") - F.col("cost") + F.col("s.kept")) - (F.col("low") + F.col("s.gone")))
    return rows.select("tile_id", "axis", "idx", "s.moved", gap.alias("gap"))


def best_of_scan(cuts: DataFrame) -> DataFrame:
    """The best cut of each tile; ties by axis (row first), side, then line."""
    key = F.struct("gap", F.when(F.col("axis") == "row", 0).otherwise(1), "moved", "idx")
    return cuts.groupBy("tile_id").agg(F.min_by(F.struct("axis", "idx", "moved", "gap"), key).alias("b")).select("tile_id", "b.*")
