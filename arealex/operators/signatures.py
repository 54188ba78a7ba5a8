"""Weights, signatures, orders and bounds of objects and queries.

An element's bound is the total weight from its place to the end of a fixed order; the order is the same on both sides. An element can matter for a threshold c only if its bound reaches c: the query's elements that do are its prefix, and an object's posting is of use under the same test.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from arealex.functions.cells import Space, cell_range, cells_of, code

#: Orders of elements: rare first is the default; the others serve comparisons.
ORDERS = ("rare", "frequent", "random", "code")
SCALE = 1_000_000
#: Counts of cells are broadcast down to this level (4**7 rows of 16 bytes).
BROADCAST_LEVEL = 7
#: Tables with an entry for each cell of a level (4**10 of 5 bytes) are sent to tasks down to this level.
DENSE_LEVEL = 10


def token_stats(objects: DataFrame, weighted: bool = True) -> DataFrame:
    """token, n_obj and w: the natural log of (objects / objects with the token) in millionths. Without weights each token has 1."""
    seen = objects.select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("n_obj"))
    if not weighted:
        return seen.withColumn("w", F.lit(SCALE).cast("bigint"))
    # One row, so the cross join adds a column.
    total = objects.agg(F.count("*").alias("_n"))
    return seen.crossJoin(F.broadcast(total)).select("token", "n_obj", F.round(F.log(F.col("_n") / F.col("n_obj")) * SCALE).cast("bigint").alias("w"))


def element_order(element: str, kind: str = "rare", count: str = "n_obj") -> list[Column]:
    """Ordering keys of elements; ties are broken by the element itself, alike on both sides."""
    if kind == "rare":
        return [F.col(count).asc(), F.col(element).asc()]
    if kind == "frequent":
        return [F.col(count).desc(), F.col(element).asc()]
    if kind == "random":
        return [F.xxhash64(F.col(element)).asc(), F.col(element).asc()]
    if kind == "code":
        return [F.col(element).asc()]
    raise ValueError(kind)


def with_bound(signature: DataFrame, owner: list[str], order: list[Column], name: str) -> DataFrame:
    """Adds the suffix total of w over each owner's elements."""
    w = Window.partitionBy(*owner).orderBy(*order).rowsBetween(Window.currentRow, Window.unboundedFollowing)
    return signature.withColumn(name, F.sum("w").over(w))


def token_signature(objects: DataFrame, stats: DataFrame) -> DataFrame:
    """object_id, token, n_obj, w."""
    return objects.select("object_id", F.explode("tokens").alias("token")).join(stats, "token")


def token_postings(objects: DataFrame, stats: DataFrame, order: str = "rare") -> DataFrame:
    """object_id, token, w, bound_t."""
    return with_bound(token_signature(objects, stats), ["object_id"], element_order("token", order), "bound_t").drop("n_obj")


def grid_signature(objects: DataFrame, space: Space, level: int) -> DataFrame:
    """object_id, cell, w (the area of the cell that the object covers)."""
    return cells_of(objects, space, level, "object_id")


def cell_stats(signature: DataFrame) -> DataFrame:
    """cell, n_obj: the objects that meet it."""
    return signature.groupBy("cell").agg(F.count("*").alias("n_obj"))


def cell_counts(objects: DataFrame, space: Space, level: int) -> DataFrame:
    """The same from the objects, without a row for each object and cell: a column's count rises at a rectangle's first cell and falls after its last, so an object has two rows for each column of cells, and sums along a column give the counts."""
    (ax, bx), (ay, by) = cell_range(space, level, "x0", "x1", 0), cell_range(space, level, "y0", "y1", 1)
    some = objects.where("x0 < x1 and y0 < y1").select(ax.alias("_ax"), bx.alias("_bx"), ay.alias("_ay"), by.alias("_by")).where("_ax <= _bx and _ay <= _by")
    step = lambda c, n: F.struct(c.alias("y"), F.lit(n).cast("bigint").alias("n"))
    ends = some.select(F.explode(F.sequence("_ax", "_bx")).alias("x"), F.array(step(F.col("_ay"), 1), step(F.col("_by") + 1, -1)).alias("e"))
    steps = ends.select("x", F.inline("e")).groupBy("x", "y").agg(F.sum("n").alias("n"))
    column = Window.partitionBy("x").orderBy("y")
    runs = steps.withColumn("n_obj", F.sum("n").over(column.rowsBetween(Window.unboundedPreceding, Window.currentRow))).withColumn("_end", F.lead("y").over(column) - 1)
    cells = runs.where("n_obj > 0").select("x", F.explode(F.sequence("y", "_end")).alias("y"), "n_obj")
    return cells.select(code(F.col("x"), F.col("y")).alias("cell"), "n_obj")


def bounded_cells(objects: DataFrame, space: Space, level: int, counts: DataFrame, wanted: DataFrame) -> DataFrame:
    """object_id, cell, bound_r of cell_postings in the order ``rare``, for the cells in ``wanted`` only (bounds are of all cells). An object's cells are made, ordered and summed inside a task, and only those wanted leave it. Tables of a level's cells are sent to tasks, so levels go down to DENSE_LEVEL."""
    import numpy as np
    import pyarrow as pa

    size = 1 << (2 * level)
    n_obj, want = np.zeros(size, np.int32), np.zeros(size, bool)
    table = counts.select("cell", "n_obj").toArrow()
    n_obj[table["cell"].to_numpy()] = table["n_obj"].to_numpy()
    want[wanted.select("cell").distinct().toArrow()["cell"].to_numpy()] = True
    shift, start, whole = space.cell_bits(level), (space.x0, space.y0), (space.x_bits, space.y_bits)

    def spread(v):
        for k, mask in ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555)):
            v = ((v << k) | v) & mask
        return v

    def made(key, low, high):
        """The wanted postings of some rectangles."""
        first = [np.maximum((low[k] - start[k]) >> shift[k], 0) for k in (0, 1)]
        last = [np.minimum((high[k] - 1 - start[k]) >> shift[k], (1 << (whole[k] - shift[k])) - 1) for k in (0, 1)]
        wide, tall = last[0] - first[0] + 1, last[1] - first[1] + 1
        many = np.where((wide > 0) & (tall > 0) & (high[0] > low[0]) & (high[1] > low[1]), wide * tall, 0)
        row = np.repeat(np.arange(len(key)), many)
        place = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
        at = first[0][row] + place % wide[row], first[1][row] + place // wide[row]
        edge = [start[k] + (at[k] << shift[k]) for k in (0, 1)]
        sides = [np.minimum(high[k][row], edge[k] + (1 << shift[k])) - np.maximum(low[k][row], edge[k]) for k in (0, 1)]
        w, cell = sides[0] * sides[1], spread(at[0]) | (spread(at[1]) << 1)
        order = np.lexsort((cell, n_obj[cell], row))
        row, cell, w = row[order], cell[order], w[order]
        upto = np.cumsum(w)  # may wrap around; differences don't
        ends = np.cumsum(many) - 1
        bound = upto[ends[row]] - upto + w
        keep = want[cell]
        return key[row[keep]], cell[keep], bound[keep]

    def work(batches):
        for batch in batches:
            key, *box = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(5))
            spans = [np.maximum(((box[k + 2] - box[k]) >> shift[k]) + 2, 1) for k in (0, 1)]
            # A piece has some 500,000 cells, or one object.
            piece = np.cumsum(np.minimum(spans[0] * spans[1], size)) // 500_000
            cuts = np.flatnonzero(np.diff(piece)) + 1
            for rows in np.split(np.arange(len(key)), cuts):
                if len(rows):
                    found = made(key[rows], [box[0][rows], box[1][rows]], [box[2][rows], box[3][rows]])
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in found], names=["object_id", "cell", "bound_r"])

    return objects.select("object_id", "x0", "y0", "x1", "y1").mapInArrow(work, "object_id bigint, cell bigint, bound_r bigint")


def cell_postings(objects: DataFrame, space: Space, level: int, order: str = "rare", counts: DataFrame | None = None) -> DataFrame:
    """object_id, cell, w, n_obj, bound_r. ``counts`` are those of all objects, where ``objects`` are some of them.

    The planner takes rows made by explode for as few as the objects and would broadcast them, so the join is told what to do: a level has a bounded number of cells, which are broadcast while they are few, and merged with beyond.
    """
    sig = grid_signature(objects, space, level)
    counts = cell_stats(sig) if counts is None else counts
    both = sig.join(F.broadcast(counts), "cell") if level <= BROADCAST_LEVEL else sig.hint("merge").join(counts, "cell")
    return with_bound(both, ["object_id"], element_order("cell", order), "bound_r")


def weighted_objects(objects: DataFrame, stats: DataFrame) -> DataFrame:
    """The objects with w_total, the weight of all their tokens."""
    totals = token_signature(objects, stats).groupBy("object_id").agg(F.sum("w").alias("w_total"))
    return objects.join(totals, "object_id", "left").withColumn("w_total", F.coalesce("w_total", F.lit(0).cast("bigint")))


def pair_bucket(token: Column, cell: Column, buckets: int | None) -> Column:
    """The element of a token and a cell: a bucket (by a hash that other engines have, too), or with no limit a 64-bit name of the pair."""
    if buckets is None:
        return F.xxhash64(token, cell)
    digest = F.md5(F.concat(token, F.lit(":"), cell.cast("string")).cast("binary"))
    return F.pmod(F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint"), F.lit(buckets).cast("bigint"))


def pair_postings(tokens: DataFrame, cells: DataFrame, buckets: int | None) -> DataFrame:
    """object_id, bucket, bound_t, bound_r: all tokens by all cells of the same object. Where pairs of an object collide in a bucket, the larger of each bound stays, so nothing is lost."""
    both = tokens.select("object_id", "token", "bound_t").join(cells.select("object_id", "cell", "bound_r"), "object_id")
    if buckets is None:
        return both
    rows = both.select("object_id", pair_bucket(F.col("token"), F.col("cell"), buckets).alias("bucket"), "bound_t", "bound_r")
    return rows.groupBy("object_id", "bucket").agg(F.max("bound_t").alias("bound_t"), F.max("bound_r").alias("bound_r"))
