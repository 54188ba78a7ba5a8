"""The space, and cells of its grid tree.

The space is the bounding rectangle of all objects, padded on each axis to a power of two, so that the edges of every cell are integers. Level l splits it into 2**l by 2**l cells; a cell's code interleaves the bits of its column and row, so its parent's code is the code shifted by two bits.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arealex.functions.similarity import SIDES, overlap_area

# Masks that spread 16 bits over the even places of 32.
_SPREAD = ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555))
MAX_LEVEL = 15


@dataclass(frozen=True)
class Space:
    """Lower corner, and the base-2 logarithms of the padded sides."""

    x0: int
    y0: int
    x_bits: int
    y_bits: int

    def cell_bits(self, level: int) -> tuple[int, int]:
        """Logarithms of a cell's sides; an axis ends at unit length."""
        return max(0, self.x_bits - level), max(0, self.y_bits - level)

    def cell_area(self, level: int) -> int:
        bx, by = self.cell_bits(level)
        return 1 << (bx + by)


def bounding_space(objects: DataFrame) -> Space:
    """One aggregate over the objects' sides; four numbers come to the driver. An empty set has a unit space."""
    r = objects.agg(F.min("x0"), F.min("y0"), F.max("x1"), F.max("y1")).first()
    if r[0] is None:
        return Space(0, 0, 0, 0)
    return Space(int(r[0]), int(r[1]), *(max(0, int(h - l - 1)).bit_length() for l, h in ((r[0], r[2]), (r[1], r[3]))))


def finest_level(space: Space) -> int:
    """The level whose cells are units: each lies wholly inside or outside of every rectangle, so the summed shared areas are the overlaps themselves."""
    return max(space.x_bits, space.y_bits)


def spread(v: Column) -> Column:
    v = v.cast("bigint")
    for shift, mask in _SPREAD:
        v = F.shiftleft(v, shift).bitwiseOR(v).bitwiseAND(F.lit(mask).cast("bigint"))
    return v


def code(cx: Column, cy: Column) -> Column:
    return spread(cx).bitwiseOR(F.shiftleft(spread(cy), 1))


def gathered(v: Column) -> Column:
    """The inverse of spread: every second bit, put together."""
    v = v.bitwiseAND(F.lit(_SPREAD[-1][1]).cast("bigint"))
    for (shift, _), mask in zip(_SPREAD[::-1], [m for _, m in _SPREAD[-2::-1]] + [0x0000FFFF], strict=True):
        v = v.bitwiseOR(F.shiftright(v, shift)).bitwiseAND(F.lit(mask).cast("bigint"))
    return v


def cell_box(space: Space, level: int, cell: str = "cell") -> tuple[Column, Column, Column, Column]:
    """The sides of a cell from its code."""
    kx, ky = space.cell_bits(level)
    left, low = F.shiftleft(gathered(F.col(cell)), kx) + space.x0, F.shiftleft(gathered(F.shiftright(cell, 1)), ky) + space.y0
    return left, low, left + (1 << kx), low + (1 << ky)


def cell_range(space: Space, level: int, low: str, high: str, axis: int) -> tuple[Column, Column]:
    """First and last cell that an interval of one axis meets, cut to the space. A point lies in one cell."""
    bits, start, whole = space.cell_bits(level)[axis], (space.x0, space.y0)[axis], (space.x_bits, space.y_bits)[axis]
    last = (1 << (whole - bits)) - 1
    a = F.shiftright((F.col(low) - start).cast("bigint"), bits)
    b = F.shiftright((F.greatest(F.col(high) - 1, F.col(low)) - start).cast("bigint"), bits)
    return F.greatest(a, F.lit(0).cast("bigint")), F.least(b, F.lit(last).cast("bigint"))


def cells_of(frame: DataFrame, space: Space, level: int, key: str, *more: str) -> DataFrame:
    """(key, more columns, cell, w): each cell that a row's rectangle meets with positive area, and that area. Explodes inside a task; nothing is shuffled."""
    if not 0 <= level <= MAX_LEVEL:
        raise ValueError(f"level {level}")
    (ax, bx), (ay, by) = cell_range(space, level, "x0", "x1", 0), cell_range(space, level, "y0", "y1", 1)
    kx, ky = space.cell_bits(level)
    some = frame.select(key, *more, *SIDES, ax.alias("_ax"), bx.alias("_bx"), ay.alias("_ay"), by.alias("_by")).where("_ax <= _bx and _ay <= _by")
    wide = some.withColumn("_cx", F.explode(F.sequence("_ax", "_bx"))).withColumn("_cy", F.explode(F.sequence("_ay", "_by")))
    left, low = F.shiftleft(F.col("_cx"), kx) + space.x0, F.shiftleft(F.col("_cy"), ky) + space.y0
    cell = (left, low, left + (1 << kx), low + (1 << ky))
    out = wide.select(key, *more, code(F.col("_cx"), F.col("_cy")).alias("cell"), overlap_area(tuple(F.col(s) for s in SIDES), cell).alias("w"))
    return out.where("w > 0")
