"""Links of a self-search, counted inside tasks.

Two linked objects share a token, and the first token that they share (in an order of all tokens) is in both prefixes; the lower corner of what their rectangles share lies in one cell. So a link is counted where objects with a prefix token and a cell are together, under its first shared token and in the cell of that corner only: once, and no pair leaves a task. Lists of a token and cell longer than BLOCK are parted into blocks, and each two blocks meet in a task of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.cells import Space, cell_range, code
from arealex.functions.similarity import SIDES, UNIT, shared_enough
from arealex.operators import probes as P
from arealex.operators.counting import _pieces, _place, _reach
from arealex.sources.shared import kept

#: Objects of a block; pairs tested at once; pairs for a task.
BLOCK, PAIRS, TASK_PAIRS = 2048, 1 << 19, 20_000_000
#: The cells of a level serve if an object meets so many of them on average at most.
CELLS_EACH = 2


def fits(ix: P.Index, tau_r_bp: int, tau_t_bp: int) -> bool:
    """Whether links are counted inside tasks: thresholds above 0, and measures that 64-bit integers can test."""
    return tau_r_bp > 0 and tau_t_bp > 0 and "cosine" not in (ix.measure, ix.region_measure)


def _level(objects: DataFrame, space: Space, deepest: int) -> int:
    """The deepest level whose cells are few for an object; the links are the same at each."""
    def many(v):
        (ax, bx), (ay, by) = cell_range(space, v, "x0", "x1", 0), cell_range(space, v, "y0", "y1", 1)
        return F.avg((bx - ax + 1) * (by - ay + 1)).alias(f"v{v}")

    means = objects.agg(*[many(v) for v in range(deepest + 1)]).first()
    return max([v for v in range(deepest + 1) if (means[v] or 0) <= CELLS_EACH], default=0)


def _posts(ix: P.Index, tau_t_bp: int, level: int) -> DataFrame:
    """token (a number), cell, object_id, sides, pos, ids and ws: an object's tokens in the common order and their weights, for each place in its prefix and each of its cells."""
    stats = kept(ix.stats.select("token", "n_obj", "w").withColumn("id", F.monotonically_increasing_id()))
    some = ix.objects.where("x0 < x1 and y0 < y1")
    words = some.select("object_id", F.explode("tokens").alias("token")).join(stats, "token").groupBy("object_id").agg(F.sort_array(F.collect_list(F.struct("n_obj", "id", "w"))).alias("t"))
    own = some.select("object_id", *SIDES).join(words, "object_id").select("object_id", *SIDES, F.col("t.id").alias("ids"), F.col("t.w").alias("ws"))
    total = lambda c: F.aggregate(c, F.lit(0).cast("bigint"), lambda s, w: s + w)
    # Bounds fall along the order, so the prefix is as many places as have one that is high enough.
    bounds = F.transform("ws", lambda w, k: total(F.slice("ws", k + 1, F.size("ws"))))
    own = kept(own.withColumn("prefix", F.size(F.filter(bounds, lambda b: shared_enough(b, total(F.col("ws")), F.lit(tau_t_bp).cast("bigint"), ix.measure)))).where("prefix > 0"))
    (ax, bx), (ay, by) = cell_range(ix.space, level, "x0", "x1", 0), cell_range(ix.space, level, "y0", "y1", 1)
    rows = own.withColumn("pos", F.explode(F.sequence(F.lit(0), F.col("prefix") - 1))).withColumn("_x", F.explode(F.sequence(ax, bx))).withColumn("_y", F.explode(F.sequence(ay, by)))
    return rows.select(F.get("ids", F.col("pos")).alias("token"), code(F.col("_x"), F.col("_y")).alias("cell"), "object_id", *SIDES, "pos", "ids", "ws")


def link_counts(ix: P.Index, tau_r_bp: int, tau_t_bp: int, deepest: int) -> DataFrame:
    """object_id and n_links of objects that have links with others of the index."""
    level = _level(ix.objects, ix.space, deepest)
    posts = _posts(ix, tau_t_bp, level)
    sizes = kept(posts.groupBy("token", "cell").agg(F.count("*").alias("n")).where("n > 1"))
    work = sizes.agg(F.coalesce(F.sum(F.col("n").cast("double") * F.col("n") / 2), F.lit(0.0))).first()[0]
    tasks = min(20_000, max(int(posts.sparkSession.conf.get("spark.sql.shuffle.partitions")), int(work // TASK_PAIRS)))
    parted = posts.hint("merge").join(sizes, ["token", "cell"]).withColumn("_k", F.ceil(F.col("n") / BLOCK).cast("int"))
    parted = parted.withColumn("part", F.pmod(F.xxhash64("object_id"), F.col("_k")).cast("int")).withColumn("_j", F.explode(F.sequence(F.lit(0), F.col("_k") - 1)))
    keys = ("token", "cell", "low", "high")
    rows = parted.select("token", "cell", F.least("part", "_j").alias("low"), F.greatest("part", "_j").alias("high"), "part", "object_id", *SIDES, "pos", "ids", "ws")
    rows = rows.repartition(tasks, *keys).sortWithinPartitions(*keys, "part")
    space, region, words = ix.space, ix.region_measure, ix.measure
    shift = space.cell_bits(level)

    def counted(t: pa.Table) -> pa.RecordBatch:
        """Links of some whole groups."""
        token, cell, low, high, part, key, x0, y0, x1, y1, pos = (t[c].to_numpy() for c in (*keys, "part", "object_id", *SIDES, "pos"))
        n = len(token)
        begins = np.append(True, (token[1:] != token[:-1]) | (cell[1:] != cell[:-1]) | (low[1:] != low[:-1]) | (high[1:] != high[:-1]))
        group = np.cumsum(begins) - 1
        begin = np.flatnonzero(begins)
        end = np.append(begin[1:], n)[group]
        # Two blocks meet each other, one block meets itself.
        second = begin + np.bincount(group, weights=part == low, minlength=len(begin)).astype(np.int64)
        first = np.where(low == high, np.arange(n) + 1, np.where(part == low, second[group], end))
        lists, weights = t["ids"].combine_chunks(), t["ws"].combine_chunks()
        many = lists.value_lengths().to_numpy().astype(np.int64)
        row = np.repeat(np.arange(n), many)
        at = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
        ids, w = np.full((many.max(), n), -1, np.int32), np.zeros((many.max(), n), np.int64)
        ids[at, row] = np.unique(lists.flatten().to_numpy(), return_inverse=True)[1]
        w[at, row] = weights.flatten().to_numpy()
        upto = np.cumsum(w[::-1], axis=0)[::-1]
        bound, total, area = upto[pos, np.arange(n)], upto[0], (x1 - x0) * (y1 - y0)
        own = _place(cell)
        found = np.zeros(n, np.int64)
        for piece in _pieces(end - first, PAIRS):
            a = np.repeat(np.arange(piece.start, piece.stop), (end - first)[piece])
            if not len(a):
                continue
            before = np.cumsum((end - first)[piece]) - (end - first)[piece]
            b = first[a] + np.arange(len(a)) - before[a - piece.start]
            use = _reach(np.minimum(bound[a], bound[b]), total[a] + total[b], tau_t_bp, words)
            a, b = a[use], b[use]
            left, bottom = np.maximum(x0[a], x0[b]), np.maximum(y0[a], y0[b])
            both = np.maximum(np.minimum(x1[a], x1[b]) - left, 0) * np.maximum(np.minimum(y1[a], y1[b]) - bottom, 0)
            use = (both > 0) & _reach(both, area[a] + area[b], tau_r_bp, region) & ((left - space.x0) >> shift[0] == own[0][a]) & ((bottom - space.y0) >> shift[1] == own[1][a])
            a, b = a[use], b[use]
            for some in np.array_split(np.arange(len(a)), len(a) * len(ids) // (4 * PAIRS) + 1):
                p, o = a[some], b[some]
                theirs, place = ids[:, o], pos[p]
                shared, earlier = np.zeros(len(p), np.int64), np.zeros(len(p), bool)
                for j in range(len(ids)):
                    mine = ids[j, p]
                    hit = theirs[0] == mine
                    for other in theirs[1:]:
                        hit |= other == mine
                    hit &= mine >= 0
                    earlier |= hit & (j < place)
                    shared += hit * w[j, p]
                link = ~earlier & _reach(shared, total[p] + total[o], tau_t_bp, words)
                found += np.bincount(p[link], minlength=n) + np.bincount(o[link], minlength=n)
        ids_, places = np.unique(key, return_inverse=True)
        sums = np.bincount(places, weights=found, minlength=len(ids_)).astype(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(ids_[sums > 0]), pa.array(sums[sums > 0])], names=["object_id", "n"])

    def work(batches):
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            # The last group may go on in the next batch.
            last = [batch[k][-1].as_py() for k in range(4)]
            same = np.logical_and.reduce([batch[k].to_numpy(zero_copy_only=False) == last[k] for k in range(4)])
            cut = int(np.argmax(same))
            if held and not cut and [held[-1][k][-1].as_py() for k in range(4)] == last:
                held.append(batch)
                continue
            yield from [counted(pa.Table.from_batches([*held, batch.slice(0, cut)]))] if held or cut else []
            held = [batch.slice(cut)]
        if held:
            yield counted(pa.Table.from_batches(held))

    return rows.mapInArrow(work, "object_id bigint, n bigint").groupBy("object_id").agg(F.sum("n").alias("n_links"))
