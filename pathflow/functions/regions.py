"""Rectangles and cells. A rectangle is (x0, y0, x1, y1); overlap is closed: touching counts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BOX = ("bl_x", "bl_y", "tr_x", "tr_y")


def checked(rect: tuple[float, float, float, float]) -> tuple[float, float, float, float]:
    x0, y0, x1, y1 = map(float, rect)
    if x0 > x1 or y0 > y1:
        raise ValueError(f"inverted rectangle {rect}")
    return x0, y0, x1, y1


def overlaps(rect, prefix: str = "") -> Column:
    """The box meets the rectangle: four comparisons. rect: four numbers or Columns."""
    x0, y0, x1, y1 = rect
    b = [F.col(prefix + c) for c in BOX]
    return (b[0] <= x1) & (b[1] <= y1) & (b[2] >= x0) & (b[3] >= y0)


def inside(rect, prefix: str = "") -> Column:
    """The box lies wholly in the rectangle."""
    x0, y0, x1, y1 = rect
    b = [F.col(prefix + c) for c in BOX]
    return (b[0] >= x0) & (b[1] >= y0) & (b[2] <= x1) & (b[3] <= y1)


def cell_index(value: Column, low: float, high: float, depth: int) -> Column:
    """Half-open cells on a grid of 2^depth; the outermost edge belongs to the last cell."""
    n = 1 << depth
    raw = F.floor((value - low) / (high - low) * n).cast("long") if high > low else F.lit(0).cast("long")
    return F.greatest(F.lit(0).cast("long"), F.least(raw, F.lit(n - 1).cast("long")))


def touched_cells(low: Column, high: Column, start: float, end: float, depth: int) -> tuple[Column, Column]:
    """First and last cell that the closed stretch low..high touches, by the cells' own corners: an end on a border touches both sides."""
    n = 1 << depth
    zero, last = F.lit(0).cast("long"), F.lit(n - 1).cast("long")
    if end <= start:
        return zero, zero

    def edge(k: Column) -> Column:
        return F.lit(start) + k * (end - start) / n

    a, b = cell_index(low, start, end, depth), cell_index(high, start, end, depth)
    a = a - (low <= edge(a)).cast("long") + (low > edge(a + 1)).cast("long")
    b = b + (high >= edge(b + 1)).cast("long") - (high < edge(b)).cast("long")
    return F.greatest(zero, F.least(a, last)), F.greatest(zero, F.least(b, last))


def _spread(c: Column) -> Column:
    """Bits to every second place: the binary digits, read in base four. One reference to `c`, so expressions stay small."""
    return F.conv(F.bin(c), 4, 10).cast("long")


def cell_path(ix: Column, iy: Column) -> Column:
    """Interleaved bits: every two bits choose a quarter, from the root down."""
    return _spread(ix).bitwiseOR(F.shiftleft(_spread(iy), 1))
