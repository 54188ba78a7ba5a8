"""Cells chosen for each token from the grid tree, under a budget, and the filter on token-and-cell pairs that uses them."""

from __future__ import annotations

import heapq
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.cells import cells_of
from arealex.operators import counting as C
from arealex.operators import probes as P
from arealex.operators import signatures as S

#: A token has at most (4 ** (level + 1) - 1) / 3 cells down to a level, so a task that chooses cells holds at most 1.4 million rows.
DEEPEST = 10
SELECTION = "token string, level int, cell bigint, n_obj bigint"


def token_cells(ix: P.Index, max_level: int) -> DataFrame:
    """token, level, cell, n_obj and covered (the sum of the areas that its objects cover), for all levels down to ``max_level``. Objects are counted on each level, as one may meet several children of a cell."""
    if max_level > DEEPEST:
        raise ValueError(f"cells are chosen down to level {DEEPEST} at most")
    return C.token_cells(ix.objects, ix.space, max_level)


def expected_sizes(ix: P.Index, cells: DataFrame, max_level: int) -> DataFrame:
    """Adds x, the expected list size at a point of the cell: covered area by cell area."""
    areas = F.create_map(*[F.lit(z) for v in range(max_level + 1) for z in (v, ix.space.cell_area(v))])
    return cells.withColumn("x", F.col("covered").cast("double") / F.element_at(areas, F.col("level")))


def cell_error(ix: P.Index, cells: DataFrame, max_level: int, mode: str = "children") -> DataFrame:
    """token, level, cell, n_obj, x and error: squared gaps between a cell's expected size and that of the cells below.

    ``children``: over its four children. ``children_weighted``: those by the finest cells under a child. ``finest``: over all cells of ``max_level``, the empty ones included.
    """
    sized = expected_sizes(ix, cells, max_level)
    if mode == "finest":
        fine = sized.where(F.col("level") == max_level).select("token", F.col("cell").alias("fine"), F.col("x").alias("fx"))
        up = F.explode(F.transform(F.sequence(F.lit(0), F.lit(max_level)), lambda v: F.struct(v.alias("level"), F.call_function("shiftright", F.col("fine"), 2 * (max_level - v)).alias("cell"))))
        sums = fine.select("token", "fx", up.alias("u")).groupBy("token", "u.level", "u.cell").agg(F.sum("fx").alias("s1"), F.sum(F.col("fx") * F.col("fx")).alias("s2"))
        n = F.pow(F.lit(4.0), max_level - F.col("level"))
        out = sized.join(sums, ["token", "level", "cell"], "left")
        s1, s2 = F.coalesce("s1", F.lit(0.0)), F.coalesce("s2", F.lit(0.0))
        return out.select("token", "level", "cell", "n_obj", "x", F.greatest(s2 - 2 * F.col("x") * s1 + n * F.col("x") * F.col("x"), F.lit(0.0)).alias("error"))
    child = sized.where("level > 0").select("token", (F.col("level") - 1).alias("level"), F.shiftright("cell", 2).alias("cell"), F.col("x").alias("cx"))
    sums = child.groupBy("token", "level", "cell").agg(F.sum("cx").alias("s1"), F.sum(F.col("cx") * F.col("cx")).alias("s2"))
    out = sized.join(sums, ["token", "level", "cell"], "left")
    x, s1, s2 = F.col("x"), F.coalesce("s1", F.lit(0.0)), F.coalesce("s2", F.lit(0.0))
    error = F.when(F.col("level") == max_level, F.lit(0.0)).otherwise(F.greatest(s2 - 2 * x * s1 + 4 * x * x, F.lit(0.0)))
    if mode == "children_weighted":
        error = error * F.when(F.col("level") < max_level, F.pow(F.lit(4.0), max_level - 1 - F.col("level"))).otherwise(0.0)
    return out.select("token", "level", "cell", "n_obj", "x", error.alias("error"))


def greedy_cells(cells: pd.DataFrame, budget: int, max_level: int, keep_empty: bool) -> list[tuple[int, int, int]]:
    """(level, cell, n_obj) of at most ``budget`` disjoint cells: from the whole space, the cell of largest error is split as long as the children fit, the split cell itself not counted."""
    size = {(v, c): (n, e) for v, c, n, e in zip(cells.level.tolist(), cells.cell.tolist(), cells.n_obj.tolist(), cells.error.tolist(), strict=True)}
    queue, chosen = [(-size.get((0, 0), (0, 0.0))[1], 0, 0)], []
    while queue:
        _, level, cell = heapq.heappop(queue)
        below = [(level + 1, 4 * cell + k) for k in range(4)] if level < max_level else []
        if not keep_empty:
            below = [b for b in below if b in size]
        if below and len(chosen) + len(queue) + len(below) <= budget:
            for b in below:
                heapq.heappush(queue, (-size.get(b, (0, 0.0))[1], *b))
        else:
            chosen.append((level, cell, size.get((level, cell), (0, 0.0))[0]))
    return chosen


def pick_quad_cells(ix: P.Index, budget: int, max_level: int, mode: str = "children", keep_empty: bool = False, total: bool = False) -> DataFrame:
    """token, level, cell, n_obj of each token's chosen cells.

    ``budget`` is for each token; with ``total`` it is for all, parted in proportion to the tokens' objects, with at least 4 each. Only aggregated cells of one token meet in a task, whose number the level bounds (DEEPEST).
    """
    cells = cell_error(ix, token_cells(ix, max_level), max_level, mode)
    if total:
        all_ = ix.stats.agg(F.sum("n_obj").alias("_all"))
        share = ix.stats.crossJoin(F.broadcast(all_)).select("token", F.greatest(F.lit(4), F.floor(budget * F.col("n_obj") / F.col("_all"))).cast("int").alias("m"))
        cells = cells.join(share, "token")
    else:
        cells = cells.withColumn("m", F.lit(budget))

    def choose(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = greedy_cells(pdf, int(pdf.m.iloc[0]), max_level, keep_empty)
        return pd.DataFrame([(pdf.token.iloc[0], *r) for r in rows], columns=["token", "level", "cell", "n_obj"])

    return cells.select("token", "level", "cell", "n_obj", "error", "m").groupBy("token").applyInPandas(choose, SELECTION)


def _tree_cells(frame: DataFrame, ix: P.Index, max_level: int, key: str) -> DataFrame:
    return reduce(DataFrame.unionByName, [cells_of(frame, ix.space, v, key).withColumn("level", F.lit(v)) for v in range(max_level + 1)])


def _quad_order():
    return [F.col("level").asc(), F.col("n_obj").asc(), F.col("cell").asc()]


def quad_postings(ix: P.Index, selection: DataFrame, max_level: int) -> DataFrame:
    """object_id, token, level, cell, bound_t, bound_r: each of an object's tokens with those of the token's cells that the object meets."""
    on = ix.tokens.select("object_id", "token", "bound_t").join(_tree_cells(ix.objects, ix, max_level, "object_id"), "object_id").join(selection, ["token", "level", "cell"])
    return S.with_bound(on, ["object_id", "token"], _quad_order(), "bound_r").drop("w", "n_obj")


def quad_prefix(ix: P.Index, q: DataFrame, selection: DataFrame, max_level: int) -> DataFrame:
    """Each prefix token with the prefix of its own cells."""
    t = P.token_prefix(ix, q).select("query_id", "token", "w_total", "tau_t_bp", "area", "tau_r_bp")
    on = t.join(_tree_cells(q, ix, max_level, "query_id"), "query_id").join(selection, ["token", "level", "cell"])
    return S.with_bound(on, ["query_id", "token"], _quad_order(), "rest").where(P._enough_r(ix, "rest"))


def quad_hits(ix: P.Index, q: DataFrame, selection: DataFrame, max_level: int) -> DataFrame:
    p = quad_prefix(ix, q, selection, max_level).drop("w", "n_obj", "rest")
    on = quad_postings(ix, selection, max_level).join(p, ["token", "level", "cell"])
    return on.where(P._enough_t(ix, "bound_t") & P._enough_r(ix, "bound_r"))


def quad_pair(ix: P.Index, q: DataFrame, selection: DataFrame, max_level: int, tested: bool = False) -> DataFrame:
    """Candidates by pairs of a token and one of its own cells; a small batch's are found inside tasks, where ``tested`` may leave out pairs whose areas aren't similar."""
    from arealex.operators import counting as C  # which needs query sets

    found = C.quad_probed(ix, q, selection, tested and C.sums_fit(ix, q)) if C.fits(ix, q, [max_level]) else None
    if found is not None:
        return found
    return P.pairs_of(quad_hits(ix, q, selection, max_level))
