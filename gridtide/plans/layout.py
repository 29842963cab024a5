"""Tiles and plans: immutable lists of tiles on the driver, small tables on the cluster."""

from __future__ import annotations

from dataclasses import dataclass, replace

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import broadcast

from gridtide.config import GridSpec

ARROW_PLAN = pa.schema(
    [("round", pa.int32()), ("tile_id", pa.int64()), ("machine_id", pa.int32()), ("cx0", pa.int32()), ("cy0", pa.int32()), ("cx1", pa.int32()), ("cy1", pa.int32())]
    + [("parent_ids", pa.list_(pa.int64())), ("prev_machine_id", pa.int32()), ("born_round", pa.int32()), ("retired_round", pa.int32())]
)


@dataclass(frozen=True)
class Tile:
    """A rectangle of cells (closed bounds) owned by one machine."""

    tile_id: int
    machine_id: int
    cx0: int
    cy0: int
    cx1: int
    cy1: int
    parent_ids: tuple[int, ...] = ()
    prev_machine_id: int | None = None
    born_round: int = 0
    retired_round: int | None = None

    @property
    def width(self) -> int:
        return self.cx1 - self.cx0 + 1

    @property
    def height(self) -> int:
        return self.cy1 - self.cy0 + 1

    @property
    def area(self) -> int:
        return self.width * self.height

    def cut(self, axis: str, after: int) -> tuple[tuple[int, int, int, int], tuple[int, int, int, int]]:
        """Bounds of both parts when cut behind local row or column ``after``."""
        if axis == "row":
            y = self.cy0 + after
            return (self.cx0, self.cy0, self.cx1, y), (self.cx0, y + 1, self.cx1, self.cy1)
        x = self.cx0 + after
        return (self.cx0, self.cy0, x, self.cy1), (x + 1, self.cy0, self.cx1, self.cy1)


def even_layout(spec: GridSpec, machines: int) -> list[Tile]:
    """Halve the largest tile across its longer side until every machine has one, or a half would be no cell."""
    tiles, fresh = [Tile(0, 0, 0, 0, spec.side - 1, spec.side - 1)], 1
    while len(tiles) < machines:
        big = max(tiles, key=lambda t: (t.area, -t.tile_id))
        axis, length = ("col", big.width) if big.width >= big.height else ("row", big.height)
        if length < 2:
            break
        tiles.remove(big)
        for bounds in big.cut(axis, (length + 1) // 2 - 1):
            tiles.append(Tile(fresh, 0, *bounds))
            fresh += 1
    tiles.sort(key=lambda t: (t.cx0, t.cy0))
    return [replace(t, machine_id=i) for i, t in enumerate(tiles)]


def next_id(tiles: list[Tile]) -> int:
    return max(t.tile_id for t in tiles) + 1


def plan_frame(spark: SparkSession, tiles: list[Tile], at_round: int = 0) -> DataFrame:
    """The plan as a table; it has as many rows as there are tiles."""
    rows = [(at_round, t.tile_id, t.machine_id, t.cx0, t.cy0, t.cx1, t.cy1, list(t.parent_ids), t.prev_machine_id, t.born_round, t.retired_round) for t in tiles]
    columns = zip(*rows, strict=True) if rows else [()] * len(ARROW_PLAN)
    # as Arrow it becomes a local relation, which costs no job to broadcast
    return spark.createDataFrame(pa.table([pa.array(c, f.type) for c, f in zip(columns, ARROW_PLAN, strict=True)], schema=ARROW_PLAN))


BROADCAST_BYTES = 64 << 20  # plans and other side tables that are broadcast at most


def small(frame: DataFrame) -> DataFrame:
    """``frame`` marked for broadcast where the optimiser's estimate of its size is within BROADCAST_BYTES, else as it is."""
    size = int(str(frame._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return broadcast(frame) if size <= BROADCAST_BYTES else frame


def probe_side(plan: DataFrame) -> DataFrame:
    """Plan columns named for joins: tile and machine ids and bounds ``t_cx0..``."""
    return plan.selectExpr("tile_id", "machine_id", "cx0 AS t_cx0", "cy0 AS t_cy0", "cx1 AS t_cx1", "cy1 AS t_cy1")


def values_sql(tiles: list[Tile], name: str = "plan") -> str:
    """The plan as an SQL common table expression."""
    rows = ", ".join(f"({t.tile_id}::BIGINT, {t.machine_id}, {t.cx0}, {t.cy0}, {t.cx1}, {t.cy1})" for t in tiles)
    return f"{name}(tile_id, machine_id, cx0, cy0, cx1, cy1) AS (VALUES {rows})"


def covers(spec: GridSpec, tiles: list[Tile]) -> bool:
    """True when every cell lies in exactly one tile."""
    seen = set()
    for t in tiles:
        for x in range(t.cx0, t.cx1 + 1):
            for y in range(t.cy0, t.cy1 + 1):
                if (x, y) in seen:
                    return False
                seen.add((x, y))
    return len(seen) == spec.side**2


def move_tiles(tiles: list[Tile], ids: set[int], receiver: int, at_round: int) -> list[Tile]:
    """Give tiles to another machine; a moved tile is a new one whose parent is the old."""
    fresh, out = next_id(tiles), []
    for t in tiles:
        if t.tile_id in ids:
            out.append(replace(t, tile_id=fresh, machine_id=receiver, parent_ids=(t.tile_id,), prev_machine_id=t.machine_id, born_round=at_round))
            fresh += 1
        else:
            out.append(t)
    return out


def split_tile(tiles: list[Tile], tile_id: int, axis: str, after: int, moved: str, receiver: int, at_round: int) -> list[Tile]:
    """Cut a tile; the ``moved`` part (first or second) goes to the receiver, both parts get new ids."""
    old = next(t for t in tiles if t.tile_id == tile_id)
    fresh, out = next_id(tiles), [t for t in tiles if t.tile_id != tile_id]
    for k, (side, bounds) in enumerate(zip(("first", "second"), old.cut(axis, after), strict=True)):
        owner = receiver if side == moved else old.machine_id
        out.append(Tile(fresh + k, owner, *bounds, parent_ids=(tile_id,), prev_machine_id=old.machine_id, born_round=at_round))
    return out


def merge_once(tiles: list[Tile], at_round: int = 0) -> list[Tile]:
    """Join the first pair (least ids) of one owner that shares a full edge; the same list if there is none."""
    ordered = sorted(tiles, key=lambda t: t.tile_id)
    for i, a in enumerate(ordered):
        for b in ordered[i + 1 :]:
            if a.machine_id != b.machine_id:
                continue
            beside = a.cy0 == b.cy0 and a.cy1 == b.cy1 and (a.cx1 + 1 == b.cx0 or b.cx1 + 1 == a.cx0)
            above = a.cx0 == b.cx0 and a.cx1 == b.cx1 and (a.cy1 + 1 == b.cy0 or b.cy1 + 1 == a.cy0)
            if beside or above:
                whole = Tile(next_id(tiles), a.machine_id, min(a.cx0, b.cx0), min(a.cy0, b.cy0), max(a.cx1, b.cx1), max(a.cy1, b.cy1), (a.tile_id, b.tile_id), a.machine_id, at_round)
                return [t for t in tiles if t not in (a, b)] + [whole]
    return tiles


def merge_tiles(tiles: list[Tile], at_round: int = 0) -> list[Tile]:
    """Merge pairs until none is left."""
    while (merged := merge_once(tiles, at_round)) is not tiles:
        tiles = merged
    return tiles
