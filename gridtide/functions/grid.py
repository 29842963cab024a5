"""Cell arithmetic and portable hashing as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridtide.config import GridSpec


def cell_of(value: Column, low: float, extent: float, side: int) -> Column:
    """Cell index of a coordinate, clamped into the grid."""
    return F.greatest(F.lit(0), F.least(F.lit(side - 1), F.floor((value - F.lit(low)) * F.lit(side) / F.lit(extent)))).cast("int")


def to_cells(frame: DataFrame, spec: GridSpec, x: str = "x", y: str = "y", suffix: str = "") -> DataFrame:
    """Add ``cx`` and ``cy`` (with a suffix) of the location columns."""
    return frame.withColumn(f"cx{suffix}", cell_of(F.col(x), spec.x_lo, spec.width, spec.side)).withColumn(
        f"cy{suffix}", cell_of(F.col(y), spec.y_lo, spec.height, spec.side)
    )


def rectangle_cells(frame: DataFrame, spec: GridSpec) -> DataFrame:
    """Cells of the corners (x0, y0) and (x1, y1)."""
    return to_cells(to_cells(frame, spec, "x0", "y0", "0"), spec, "x1", "y1", "1")


def word(ident: str, salt: str) -> Column:
    """28 hash bits of an id, equal in every engine that has md5."""
    return F.conv(F.substring(F.md5(F.concat(F.col(ident).cast("string"), F.lit(f":{salt}"))), 1, 7), 16, 10).cast("long")


def byte_sum(ident: str, salt: str) -> Column:
    """Sum of the first twelve md5 bytes of an id: nearly normal, mean 1530."""
    digest = F.md5(F.concat(F.col(ident).cast("string"), F.lit(f":{salt}")))
    total = F.lit(0)
    for k in range(12):
        total = total + F.conv(F.substring(digest, 2 * k + 1, 2), 16, 10).cast("long")
    return total


def overlaps(a: str = "", b: str = "t_") -> Column:
    """Closed cell rectangles ``{a}cx0..`` and ``{b}cx0..`` share a cell."""
    c = F.col
    return (c(f"{a}cx0") <= c(f"{b}cx1")) & (c(f"{a}cx1") >= c(f"{b}cx0")) & (c(f"{a}cy0") <= c(f"{b}cy1")) & (c(f"{a}cy1") >= c(f"{b}cy0"))


def holds(b: str = "t_") -> Column:
    """Cell (cx, cy) lies in the rectangle ``{b}cx0..``."""
    c = F.col
    return c("cx").between(c(f"{b}cx0"), c(f"{b}cx1")) & c("cy").between(c(f"{b}cy0"), c(f"{b}cy1"))
