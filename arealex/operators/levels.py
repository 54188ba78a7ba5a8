"""Cost-based choice of a grid level.

All levels are looked at in one pass: a level's expected cost for a workload is pi1 times the postings that its queries retrieve on average (a cell's chance of use by its list length) plus pi2 times the mean number of candidates.
"""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from arealex.functions.cells import cells_of
from arealex.operators import probes as P
from arealex.operators import signatures as S
from arealex.operators.verify import verify

PI1, PI2 = 1.0, 10.0


def query_cost(retrieved, candidates, pi1: float = PI1, pi2: float = PI2):
    """pi1 * postings retrieved + pi2 * candidates, for columns or numbers."""
    return pi1 * retrieved + pi2 * candidates


def calibrate_costs(ix: P.Index, workload: DataFrame, level: int) -> tuple[float, float]:
    """Seconds for a posting retrieved and for a candidate verified, measured on a workload; their ratio is what the choice of a level needs in place of PI1 and PI2."""
    began = time.perf_counter()
    hits = P.grid_bounded_hits(ix, workload, level).count()
    retrieved = time.perf_counter()
    pairs = P.grid_bounded(ix, workload, level)
    n = pairs.count()
    found = time.perf_counter()
    verify(ix, workload, pairs).count()
    return (retrieved - began) / max(1, hits), max(0.0, time.perf_counter() - found - (found - retrieved)) / max(1, n)


def _every(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def level_cells(ix: P.Index, levels: list[int]) -> DataFrame:
    """level, cell, n_obj."""
    return _every([S.cell_stats(S.grid_signature(ix.objects, ix.space, v)).select(F.lit(v).alias("level"), "cell", "n_obj") for v in levels])


def cell_usage(ix: P.Index, workload: DataFrame, levels: list[int], prefix: bool = False) -> DataFrame:
    """level, cell, used: how many of the workload's queries use the cell; with ``prefix``, as one of their prefix."""
    if prefix:
        parts = [P.cell_prefix(ix, workload, v).select(F.lit(v).alias("level"), "cell") for v in levels]
    else:
        parts = [cells_of(workload, ix.space, v, "query_id").select(F.lit(v).alias("level"), "cell") for v in levels]
    return _every(parts).groupBy("level", "cell").agg(F.count("*").alias("used"))


def expected_level_cost(ix: P.Index, workload: DataFrame, levels: list[int], prefix: bool = False, pi1: float = PI1, pi2: float = PI2) -> DataFrame:
    """level, retrieved and candidates (sums over the workload), and cost for a mean query. A list counts whole, which is the worst case."""
    n = workload.count()
    lists = cell_usage(ix, workload, levels, prefix).join(level_cells(ix, levels), ["level", "cell"])
    retrieved = lists.groupBy("level").agg(F.sum(F.col("used") * F.col("n_obj")).alias("retrieved"))
    found = _every([P.grid_bounded(ix, workload, v).agg(F.count("*").alias("candidates")).withColumn("level", F.lit(v)) for v in levels])
    out = found.join(retrieved, "level", "left").withColumn("retrieved", F.coalesce("retrieved", F.lit(0).cast("bigint")))
    return out.select("level", "retrieved", "candidates", F.round(query_cost(F.col("retrieved"), F.col("candidates"), pi1, pi2) / n, 6).alias("cost"))


def level_benefits(costs: DataFrame) -> DataFrame:
    """level and benefit: what going one level down saves. A row for each level."""
    w = Window.orderBy("level")
    return costs.withColumn("benefit", F.round(F.col("cost") - F.lead("cost").over(w), 6)).select("level", "cost", "benefit")


def cell_filter_benefit(ix: P.Index, workload: DataFrame, level: int, pi1: float = PI1) -> DataFrame:
    """cell and benefit of splitting each used cell of a level: pi1 * (its chance by its list length, less the same over its children)."""
    n = workload.count()
    weight = F.col("used") * F.col("n_obj")
    both = cell_usage(ix, workload, [level, level + 1]).join(level_cells(ix, [level, level + 1]), ["level", "cell"])
    own = both.where(F.col("level") == level).select("cell", weight.alias("own"))
    below = both.where(F.col("level") == level + 1).groupBy(F.shiftright("cell", 2).alias("cell")).agg(F.sum(weight).alias("below"))
    return own.join(below, "cell", "left").select("cell", F.round(pi1 * (F.col("own") - F.coalesce("below", F.lit(0))) / n, 6).alias("benefit"))


def pick_level(costs: DataFrame, min_benefit: float) -> DataFrame:
    """The first level from the top whose split saves less than ``min_benefit``; the last one if none does."""
    b = level_benefits(costs)
    return b.agg(F.coalesce(F.min(F.when(F.col("benefit") < min_benefit, F.col("level"))), F.max("level")).alias("level"))


def best_level(costs: DataFrame) -> DataFrame:
    """The level of least cost."""
    return costs.agg(F.min(F.struct("cost", "level")).alias("b")).select(F.col("b.level").alias("level"), F.col("b.cost").alias("cost"))
