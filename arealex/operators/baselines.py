"""Baselines: words first, area first, and a tree whose nodes hold rectangles and words."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from arealex.functions.cells import cells_of, code
from arealex.functions.similarity import SIDES, area, at_least, box, overlap_area
from arealex.operators import probes as P
from arealex.operators import signatures as S
from arealex.operators.verify import verify
from arealex.sources.shared import kept


def word_first(ix: P.Index, q: DataFrame) -> DataFrame:
    """Pairs whose words are similar, from inverted lists with exact sums; areas are tested afterwards. A small batch's sums are made inside tasks, so no row is made for a pair that shares a token."""
    from arealex.operators import counting as C  # which needs query sets, and these need ranks

    if C.sums_fit(ix, q):
        return verify(ix, q, C.word_first_pairs(ix, q))
    sums = P.token_overlap(ix, q)
    totals = ix.full.select("object_id", F.col("w_total").alias("o_w"))
    mine = ix.prepared(q).select("query_id", "w_total", "tau_t_bp")
    near = sums.join(totals, "object_id").join(mine, "query_id").where(at_least(F.col("inter_w"), F.col("w_total"), F.col("o_w"), F.col("tau_t_bp"), ix.measure))
    return verify(ix, q, near)


def near_areas(ix: P.Index, q: DataFrame, index: str = "grid", level: int = 6) -> DataFrame:
    """Pairs whose areas are similar: by an equi-join on cells (inside tasks for a small batch), by descent of the tree, or by a scan of a bounded batch."""
    from arealex.operators import counting as C  # which needs query sets, and these need ranks

    mine = q.select("query_id", *[F.col(s).alias(f"q_{s}") for s in SIDES], "tau_r_bp")
    if index == "grid" and C.sums_fit(ix, q):
        return C.met_areas(ix, q, level)
    if index == "grid":
        own = cells_of(q, ix.space, level, "query_id").select("query_id", "cell")
        met = own.join(S.grid_signature(ix.objects, ix.space, level).select("object_id", "cell"), "cell").select("query_id", "object_id").distinct()
        both = met.join(mine, "query_id").join(ix.objects.select("object_id", *SIDES), "object_id")
    elif index == "scan":
        both = ix.objects.select("object_id", *SIDES).crossJoin(F.broadcast(P.bounded(mine)))
    elif index == "tree":
        met = word_tree_candidates(ix, q, use_words=False)
        both = met.join(mine, "query_id").join(ix.objects.select("object_id", *SIDES), "object_id")
    else:
        raise ValueError(index)
    a, b = box("q_"), box()
    return both.where(at_least(overlap_area(a, b), area(a), area(b), F.col("tau_r_bp"), ix.region_measure)).select("query_id", "object_id")


def area_first(ix: P.Index, q: DataFrame, index: str = "grid", level: int = 6) -> DataFrame:
    return verify(ix, q, near_areas(ix, q, index, level))


def _below(cuts: list[float], key: Column, low: int, high: int) -> Column:
    """How many of the sorted cuts are below the key, by halves."""
    if low == high:
        return F.lit(low)
    mid = (low + high) // 2
    return F.when(F.lit(float(cuts[mid])) < key, _below(cuts, key, mid + 1, high)).otherwise(_below(cuts, key, low, mid))


def ranked(frame: DataFrame, key: str, ties: str, buckets: int = 256, below: int | None = None) -> DataFrame:
    """Adds rank, from 0, in the order of (key, ties), without sorting all rows in one task: rows fall into ranges of the key between sampled quantiles, and a row's rank is its place in the range after the sizes of the ranges before. Ranges that begin at ``below`` or later are left out before they are sorted."""
    cuts = sorted(set(frame.approxQuantile(key, [k / buckets for k in range(1, buckets)], 0.001)))
    rows = frame.withColumn("_part", _below(cuts, F.col(key), 0, len(cuts)))
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)  # one row for each range
    sizes = rows.groupBy(F.col("_part").alias("_p")).agg(F.count("*").alias("_n")).withColumn("_before", F.coalesce(F.sum("_n").over(before), F.lit(0)))
    sizes = sizes if below is None else sizes.where(F.col("_before") < below)
    own = F.row_number().over(Window.partitionBy("_part").orderBy(key, ties)) - 1
    placed = rows.join(F.broadcast(sizes.select("_p", "_before")), F.col("_part") == F.col("_p")).withColumn("rank", F.col("_before") + own)
    return placed.drop("_part", "_p", "_before")


#: Up to so many pairs of a query and a node are sent to all tasks.
FEW_NODES = 500_000


def word_tree_levels(ix: P.Index, fanout: int = 32, objects: DataFrame | None = None) -> tuple[dict[int, DataFrame], int]:
    """Nodes of each level (node_id, parent_id, sides, tokens) and the height. Level 0 has the objects; neighbours on a space-filling curve through their centres share a parent. A level is made of the one below."""
    o = ix.objects if objects is None else objects
    kx, ky = ix.space.cell_bits(15)
    cx = F.shiftright(F.shiftright(F.col("x0") + F.col("x1") - 2 * ix.space.x0, 1), kx)
    cy = F.shiftright(F.shiftright(F.col("y0") + F.col("y1") - 2 * ix.space.y0, 1), ky)
    placed = kept(ranked(o.withColumn("curve", code(cx, cy)), "curve", "object_id").select("object_id", "rank", *SIDES, "tokens"))
    n, height = ix.count(), 1
    while fanout**height < n:
        height += 1
    up = lambda c: F.floor(F.col(c) / fanout).cast("bigint")
    levels = {0: placed.select(F.col("object_id").alias("node_id"), up("rank").alias("parent_id"), *SIDES, F.array_distinct("tokens").alias("tokens"))}
    heads, said = placed.select(up("rank").alias("node_id"), *SIDES), placed.select(up("rank").alias("node_id"), F.explode("tokens").alias("token"))
    for level in range(1, height + 1):
        box_of = [f(c).alias(c) for c, f in zip(SIDES, (F.min, F.min, F.max, F.max), strict=True)]
        heads, said = kept(heads.groupBy("node_id").agg(*box_of)), kept(said.distinct())
        parent = up("node_id") if level < height else F.col("node_id")
        words = said.groupBy("node_id").agg(F.collect_list("token").alias("tokens"))
        levels[level] = heads.join(words, "node_id", "left").select("node_id", parent.alias("parent_id"), *SIDES, "tokens")
        heads, said = heads.select(up("node_id").alias("node_id"), *SIDES), said.select(up("node_id").alias("node_id"), "token")
    return levels, height


def word_tree(ix: P.Index, fanout: int = 32, objects: DataFrame | None = None) -> tuple[DataFrame, DataFrame, int]:
    """tree_nodes (level, node_id, parent_id, sides), tree_words (level, node_id, token) and the height."""
    levels, height = word_tree_levels(ix, fanout, objects)
    nodes = [n.select(F.lit(v).alias("level"), "node_id", "parent_id", *SIDES) for v, n in levels.items()]
    words = [n.select(F.lit(v).alias("level"), "node_id", F.explode("tokens").alias("token")) for v, n in levels.items()]
    return reduce(DataFrame.unionByName, nodes), reduce(DataFrame.unionByName, words), height


def kept_tree(ix: P.Index, fanout: int) -> tuple[dict[int, DataFrame], int]:
    """The tree, written once, a table for each level: a node's words are in its row, so that no row is made for an object's word where objects are."""
    levels, height = word_tree_levels(ix, fanout)
    return {v: kept(n) if v else n for v, n in levels.items()}, height


def word_tree_visits(ix: P.Index, q: DataFrame, fanout: int = 32, use_words: bool = True) -> list[tuple[int, DataFrame]]:
    """(level, frontier) from below the root to the objects: nodes whose shared area and shared words both reach the query's thresholds. One join a level, as many as the logarithm of the number of objects."""
    levels, height = ix._once(("tree", fanout), lambda: kept_tree(ix, fanout))
    mine = ix.prepared(q).select("query_id", *[F.col(s).alias(f"q_{s}") for s in SIDES], "area", "w_total", "weights", "tau_r_bp", "tau_t_bp")
    mine = F.broadcast(mine) if P.is_small(q) else mine
    shared = F.aggregate(F.filter("tokens", lambda t: F.map_contains_key("weights", t)), F.lit(0).cast("bigint"), lambda n, t: n + F.element_at("weights", t))
    frontier, out, few = None, [], True
    for level in range(height, -1, -1):
        there = levels[level]
        # A node is read for few queries' sake where it lies, and not shuffled.
        rows = there.crossJoin(F.broadcast(mine)) if frontier is None else there.join(F.broadcast(frontier) if few else frontier, "parent_id").join(mine, "query_id")
        rows = rows.withColumn("_shared", overlap_area(box("q_"), box())).where(P.shared_enough(F.col("_shared"), F.col("area"), F.col("tau_r_bp"), ix.region_measure))
        if use_words:
            rows = rows.where(P.shared_enough(shared, F.col("w_total"), F.col("tau_t_bp"), ix.measure))
        # Written, as the next level reads it twice, and the one below that four times.
        rows = kept(rows.select("query_id", "node_id"))
        few = rows.limit(FEW_NODES + 1).count() <= FEW_NODES
        out.append((level, rows))
        frontier = rows.select("query_id", F.col("node_id").alias("parent_id"))
    return out


def word_tree_candidates(ix: P.Index, q: DataFrame, fanout: int = 32, use_words: bool = True) -> DataFrame:
    return word_tree_visits(ix, q, fanout, use_words)[-1][1].withColumnRenamed("node_id", "object_id")


def word_tree_search(ix: P.Index, q: DataFrame, fanout: int = 32) -> DataFrame:
    return verify(ix, q, word_tree_candidates(ix, q, fanout))
