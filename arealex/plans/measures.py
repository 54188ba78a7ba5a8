"""Cost measures of methods and statistics of object sets."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.cells import cells_of
from arealex.functions.similarity import SIDES, area, box, overlap_area
from arealex.operators import baselines as B
from arealex.operators import probes as P
from arealex.operators import quadcells as Q
from arealex.operators import signatures as S
from arealex.operators.levels import query_cost
from arealex.operators.verify import verify
from arealex.sources.shared import kept


def dataset_stats(ix: P.Index) -> DataFrame:
    """One row: objects, distinct tokens, tokens and area in all, and the padded space."""
    o = ix.objects.agg(F.count("*").alias("objects"), F.sum(area(box())).alias("area_sum"), F.sum(F.size("tokens")).cast("bigint").alias("tokens_sum"))
    t = ix.stats.agg(F.count("*").alias("distinct_tokens"))
    return o.crossJoin(F.broadcast(t)).withColumn("space_area", F.lit(ix.space.cell_area(0)).cast("bigint"))


def area_distribution(ix: P.Index) -> DataFrame:
    """decade and objects with an area of that many digits, with the running count."""
    from pyspark.sql import Window

    digits = F.length(area(box()).cast("string")).cast("bigint")
    d = ix.objects.groupBy(digits.alias("digits")).agg(F.count("*").alias("objects"))
    return d.withColumn("upto", F.sum("objects").over(Window.orderBy("digits").rowsBetween(Window.unboundedPreceding, Window.currentRow)))


def overlap_count(ix: P.Index, q: DataFrame, level: int = 6) -> DataFrame:
    """query_id and n_overlap: the objects that share area with a query."""
    own = cells_of(q, ix.space, level, "query_id").select("query_id", "cell")
    met = own.join(S.grid_signature(ix.objects, ix.space, level).select("object_id", "cell"), "cell").select("query_id", "object_id").distinct()
    both = met.join(q.select("query_id", *[F.col(s).alias(f"q_{s}") for s in SIDES]), "query_id").join(ix.objects.select("object_id", *SIDES), "object_id")
    return both.where(overlap_area(box("q_"), box()) > 0).groupBy("query_id").agg(F.count("*").alias("n_overlap"))


def candidate_count(candidates: DataFrame) -> DataFrame:
    return candidates.groupBy("query_id").agg(F.count("*").alias("candidates"))


def probe_cost(hits: DataFrame, prefix: DataFrame, pi1: float = 1.0, pi2: float = 10.0) -> DataFrame:
    """query_id, lists (elements looked up), retrieved (postings of use in them), candidates and cost."""
    r = hits.groupBy("query_id").agg(F.count("*").alias("retrieved"), F.count_distinct("object_id").alias("candidates"))
    p = prefix.groupBy("query_id").agg(F.count("*").alias("lists"))
    out = p.join(r, "query_id", "left").na.fill(0, ["retrieved", "candidates"])
    return out.select("query_id", "lists", "retrieved", "candidates", F.round(query_cost(F.col("retrieved"), F.col("candidates"), pi1, pi2), 6).alias("cost"))


def filter_quality(ix: P.Index, q: DataFrame, candidates: DataFrame) -> DataFrame:
    """One row: candidates, answers, and answers that are not candidates (none, if the filter is sound)."""
    truth = verify(ix, q).select("query_id", "object_id")
    missed = truth.join(candidates, ["query_id", "object_id"], "left_anti").agg(F.count("*").alias("missed"))
    return candidates.agg(F.count("*").alias("candidates")).crossJoin(truth.agg(F.count("*").alias("answers"))).crossJoin(missed)


def bound_tightness(ix: P.Index, q: DataFrame, level: int) -> DataFrame:
    """query_id, bound_sum and true_sum: over pairs that share a cell, the summed cell bounds and the true overlaps."""
    pairs = P.grid_overlap_hits(ix, q, level).groupBy("query_id", "object_id").agg(F.sum(F.least("w", "w_q")).alias("bound"))
    both = pairs.join(q.select("query_id", *[F.col(s).alias(f"q_{s}") for s in SIDES]), "query_id").join(ix.objects.select("object_id", *SIDES), "object_id")
    return both.groupBy("query_id").agg(F.sum("bound").alias("bound_sum"), F.sum(overlap_area(box("q_"), box())).alias("true_sum"))


def index_size(ix: P.Index, levels: list[int], buckets: int | None = 1 << 16, budget: int = 64, max_level: int = 5) -> DataFrame:
    """kind, elements and postings of each index."""

    def row(kind: str, postings: DataFrame, *element: str) -> DataFrame:
        return postings.agg(F.lit(kind).alias("kind"), F.count_distinct(*element).alias("elements"), F.count("*").alias("postings"))

    out = row("token", ix.tokens, "token")
    for v in levels:
        out = out.unionByName(row(f"grid{v}", ix.cells(v), "cell"))
        out = out.unionByName(row(f"pair{v}", S.pair_postings(ix.tokens, ix.cells(v), None), "token", "cell"))
        if buckets:
            out = out.unionByName(row(f"hashed{v}", S.pair_postings(ix.tokens, ix.cells(v), buckets), "bucket"))
    if budget:
        out = out.unionByName(row("quad", Q.quad_postings(ix, Q.pick_quad_cells(ix, budget, max_level), max_level), "token", "level", "cell"))
    return out


def split_seconds(ix: P.Index, q: DataFrame, candidates: Callable[[], DataFrame]) -> tuple[float, float, int, int]:
    """Seconds for the filter (its candidates written once) and for the verification of what it left, candidates and answers."""
    began = time.perf_counter()
    found = kept(candidates().select("query_id", "object_id"))
    filtered = time.perf_counter()
    answers = verify(ix, q, found).count()
    return filtered - began, time.perf_counter() - filtered, found.count(), answers


def nodes_visited(ix: P.Index, q: DataFrame, fanout: int = 32) -> DataFrame:
    """level and visited: tree nodes taken by all queries."""
    from functools import reduce

    rows = [f.agg(F.count("*").alias("visited")).select(F.lit(v).alias("level"), "visited") for v, f in B.word_tree_visits(ix, q, fanout)]
    return reduce(DataFrame.unionByName, rows)
