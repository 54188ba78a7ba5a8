"""Exact tests of candidate pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.similarity import SIDES, area, at_least, box, overlap_area, shared_enough
from arealex.operators.probes import Index, bounded
from arealex.sources.shared import kept

#: Up to so many pairs, their objects' ids are sent to all tasks.
FEW_PAIRS = 1_000_000

ANSWER = ("query_id", "object_id", "inter_area", "union_area", "inter_w", "union_w")


def _counted(pairs: DataFrame) -> tuple[DataFrame, bool]:
    """The pairs, written once, and whether they are few: the objects are then scanned for them and not shuffled."""
    pairs = kept(pairs.select("query_id", "object_id"))
    return pairs, pairs.limit(FEW_PAIRS + 1).count() <= FEW_PAIRS


def measured(ix: Index, queries: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """inter_area, union_area, inter_w and union_w of pairs, with the totals; without ``pairs``, of each query with each object. Pairs that can't be answers are left out.

    Rectangles come first: an object's tokens are looked at only where the areas pass. The weights of shared tokens are looked up in the query's own map, and an object's own total is summed last, for pairs that share enough for the query's.
    """
    known = "full" in ix._made
    pairs, few = (pairs, False) if pairs is None else _counted(pairs)
    q = ix.prepared(queries).select("query_id", *[F.col(s).alias(f"q_{s}") for s in SIDES], F.col("area").alias("q_area"), F.col("w_total").alias("q_w"), "weights", "tau_r_bp", "tau_t_bp")
    o = (ix.full if known else ix.objects).select("object_id", *SIDES, area(box()).alias("o_area"), *([F.col("w_total").alias("o_w")] if known else []), "tokens")
    if few:
        o = o.join(F.broadcast(pairs.select("object_id").distinct()), "object_id", "left_semi")
    rows = o.crossJoin(F.broadcast(q)) if pairs is None else pairs.join(q, "query_id").join(o, "object_id")
    rows = rows.withColumn("inter_area", overlap_area(box("q_"), box())).where(at_least(F.col("inter_area"), F.col("q_area"), F.col("o_area"), F.col("tau_r_bp"), ix.region_measure))
    shared = F.aggregate(F.filter("tokens", lambda t: F.map_contains_key("weights", t)), F.lit(0).cast("bigint"), lambda s, t: s + F.element_at("weights", t))
    rows = rows.withColumn("inter_w", shared)
    if known:
        return rows
    if ix.own_weights:
        rows = rows.where(shared_enough(F.col("inter_w"), F.col("q_w"), F.col("tau_t_bp"), ix.measure))
    values = ("q_area", "q_w", "tau_r_bp", "tau_t_bp", "o_area", "inter_area", "inter_w")
    each = rows.select("query_id", "object_id", *values, F.explode_outer("tokens").alias("token")).join(ix.stats.select("token", "w"), "token", "left")
    return each.groupBy("query_id", "object_id").agg(*[F.any_value(c).alias(c) for c in values], F.coalesce(F.sum("w"), F.lit(0).cast("bigint")).alias("o_w"))


def verify(ix: Index, queries: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """The answers among ``pairs``: both similarities reach the query's thresholds."""
    ok = at_least(F.col("inter_w"), F.col("q_w"), F.col("o_w"), F.col("tau_t_bp"), ix.measure)
    out = measured(ix, queries, pairs).where(ok)
    return out.select("query_id", "object_id", "inter_area", (F.col("q_area") + F.col("o_area") - F.col("inter_area")).alias("union_area"), "inter_w", (F.col("q_w") + F.col("o_w") - F.col("inter_w")).alias("union_w"))


def exact_scan(ix: Index, queries: DataFrame) -> DataFrame:
    """All objects against a stated batch of queries, which is broadcast: brute force, for reference."""
    return verify(ix, bounded(queries))
