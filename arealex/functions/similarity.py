"""Similarity of rectangles and of weighted word sets, as column expressions on integers.

Thresholds are basis points (4000 is 0.4), so that each test is an integer inequality and means the same in every engine and order of summation.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SIDES = ("x0", "y0", "x1", "y1")
UNIT = 10_000


def box(prefix: str = "") -> tuple[Column, Column, Column, Column]:
    """The four side columns of a rectangle whose names have a prefix."""
    return tuple(F.col(prefix + s) for s in SIDES)


def area(r: tuple[Column, ...]) -> Column:
    return (r[2] - r[0]) * (r[3] - r[1])


def overlap_area(a: tuple[Column, ...], b: tuple[Column, ...]) -> Column:
    """Area that two rectangles share, 0 if they are apart or only touch."""
    wide = F.least(a[2], b[2]) - F.greatest(a[0], b[0])
    high = F.least(a[3], b[3]) - F.greatest(a[1], b[1])
    return F.greatest(wide, F.lit(0)) * F.greatest(high, F.lit(0))


def ratio(shared: Column, a: Column, b: Column, measure: str = "jaccard") -> Column:
    """Similarity of two sets of weights ``a`` and ``b`` that share ``shared``; 0 where it is undefined."""
    if measure == "jaccard":
        low = a + b - shared
        return F.when(low > 0, shared.cast("double") / low).otherwise(F.lit(0.0))
    if measure == "dice":
        return F.when(a + b > 0, 2 * shared.cast("double") / (a + b)).otherwise(F.lit(0.0))
    if measure == "cosine":
        return F.when((a > 0) & (b > 0), shared.cast("double") / F.sqrt(a.cast("double") * b)).otherwise(F.lit(0.0))
    raise ValueError(measure)


def at_least(shared: Column, a: Column, b: Column, bp: Column, measure: str = "jaccard") -> Column:
    """ratio(...) >= bp / 10000 without division."""
    none = bp <= 0
    if measure == "jaccard":
        return none | ((a + b - shared > 0) & (UNIT * shared >= bp * (a + b - shared)))
    if measure == "dice":
        return none | ((a + b > 0) & (2 * UNIT * shared >= bp * (a + b)))
    if measure == "cosine":
        # Squares of totals up to 1e14 (a hundred million nats in millionths) times 1e8 fit into 38 digits.
        wide = lambda c: c.cast("decimal(14,0)")
        return none | ((a > 0) & (b > 0) & (F.lit(UNIT * UNIT).cast("decimal(9,0)") * (wide(shared) * wide(shared)) >= (bp * bp).cast("decimal(9,0)") * (wide(a) * wide(b))))
    raise ValueError(measure)


def shared_enough(shared: Column, own: Column, bp: Column, measure: str = "jaccard") -> Column:
    """What a similar pair shares at least, told from the query's own total: the filters' threshold.

    The other total is at least what is shared, so Jaccard's bound is bp * own; Dice's is bp / (2 - bp) * own and cosine's is bp squared * own.
    """
    if measure == "jaccard":
        return UNIT * shared >= bp * own
    if measure == "dice":
        return (2 * UNIT - bp) * shared >= bp * own
    if measure == "cosine":
        return F.lit(UNIT * UNIT).cast("bigint") * shared >= bp * bp * own
    raise ValueError(measure)
