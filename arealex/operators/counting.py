"""What a small batch's bounded probes retrieve, counted inside tasks.

A sweep needs the number of postings that a query retrieves of an object, not the postings. In the order of elements both the query's prefix and the object's postings of use are beginnings, so a pair of them retrieves the shared elements up to the earlier of two places: one place for a query and threshold (its prefix), one for an object and what the query needs (its bounds). The batch's places and a level's places of cells are sent to tasks; an object's postings are made, ordered and summed there, and only sums leave.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.cells import Space
from arealex.functions.similarity import SIDES, UNIT
from arealex.operators import probes as P
from arealex.operators import signatures as S
from arealex.sources.querysets import with_thresholds

#: Weights of up to this many tokens are sent to tasks.
VOCABULARY = 100_000
#: Objects counted at once (areas of 2**48 add up to less than 2**63), and cells or bounds held for them.
ROWS, HELD = 4096, 2_000_000
#: An object with more cells is ordered by itself, others together.
ALONE = 400
#: The place of a cell that no object meets.
UNMET = np.iinfo(np.int32).max


def least_shared(own: int, bp: int, measure: str) -> int:
    """The least integer that passes ``shared_enough``."""
    up = {"jaccard": (bp * own, UNIT), "dice": (bp * own, 2 * UNIT - bp), "cosine": (bp * bp * own, UNIT * UNIT)}[measure]
    return -(-up[0] // up[1])


def fits(ix: P.Index, q: DataFrame, levels: list[int]) -> bool:
    """Whether a batch is counted inside tasks: bounds are those of the order ``rare``, and tables of cells and tokens small."""
    return ix.order == "rare" and max(levels, default=0) <= S.DENSE_LEVEL and P.is_small(q) and ix.stats.limit(VOCABULARY + 1).count() <= VOCABULARY


def places(level: int, counts: DataFrame) -> np.ndarray:
    """Each cell's place in the order, by row and column; cells that no object meets come last."""
    table = counts.select("cell", "n_obj").toArrow()
    cell, n = table["cell"].to_numpy(), table["n_obj"].to_numpy()
    place = np.full(1 << (2 * level), UNMET, np.int32)
    place[cell[np.lexsort((cell, n))]] = np.arange(len(cell), dtype=np.int32)
    half = np.arange(1 << level, dtype=np.int64)
    return place[_code(half[None, :], half[:, None])]


def _code(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Codes of cells by column and row."""
    for shift, mask in ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555)):
        x, y = ((x << shift) | x) & mask, ((y << shift) | y) & mask
    return x | (y << 1)


def _place(code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Columns and rows of cells by their codes."""
    x, y = code & 0x55555555, (code >> 1) & 0x55555555
    for shift, mask in ((1, 0x33333333), (2, 0x0F0F0F0F), (4, 0x00FF00FF), (8, 0x0000FFFF)):
        x, y = ((x >> shift) | x) & mask, ((y >> shift) | y) & mask
    return x, y


def _ranges(space: Space, level: int, box: list[np.ndarray]) -> tuple[list[np.ndarray], list[np.ndarray], np.ndarray]:
    """First and last cells of rectangles on both axes, and which rectangles have cells."""
    shift, whole = space.cell_bits(level), (space.x_bits, space.y_bits)
    first = [np.maximum((box[k] - s) >> shift[k], 0) for k, s in enumerate((space.x0, space.y0))]
    last = [np.minimum((box[k + 2] - 1 - s) >> shift[k], (1 << (whole[k] - shift[k])) - 1) for k, s in enumerate((space.x0, space.y0))]
    return first, last, (box[0] < box[2]) & (box[1] < box[3]) & (first[0] <= last[0]) & (first[1] <= last[1])


def _pieces(sizes: np.ndarray, most: int):
    """Runs of rows whose sizes add up to some ``most``, or single rows."""
    cuts = np.flatnonzero(np.diff(np.cumsum(sizes) // most)) + 1
    return [slice(a, b) for a, b in zip([0, *cuts], [*cuts, len(sizes)], strict=True) if a < b]


def _unrolled(first, last) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Row, column number and row number of each cell of some ranges, and the cells before each range."""
    wide, many = last[0] - first[0] + 1, (last[0] - first[0] + 1) * (last[1] - first[1] + 1)
    begin = np.cumsum(many) - many
    row = np.repeat(np.arange(len(many)), many)
    at = np.arange(len(row)) - begin[row]
    return row, first[0][row] + at % wide[row], first[1][row] + at // wide[row], np.append(begin, len(row))


class GridSide:
    """The cells of one level: for a batch of objects, the pairs that may meet and their postings under each threshold."""

    def __init__(self, space: Space, level: int, place: np.ndarray, box: list[np.ndarray], need: np.ndarray):
        self.space, self.level, self.place, self.need = space, level, place, need
        self.first, self.last, self.real = _ranges(space, level, box)
        #: The place of the last cell of each query's prefix, which has cells that some object meets.
        self.cut = np.full(need.shape, -1, np.int64)
        for j in np.flatnonzero(self.real):
            own, weight = self._ordered(*[[v[j] for v in side] for side in (box, self.first, self.last)])
            weight = weight[own < UNMET]
            if len(weight):
                upto = np.cumsum(weight)
                self.cut[:, j] = self._upto(own, upto - weight, 0, len(weight), upto[-1] - need[:, j])

    def _sides(self, k: int, at: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        shift = self.space.cell_bits(self.level)[k]
        edge = (self.space.x0, self.space.y0)[k] + (at << shift)
        return np.minimum(high, edge + (1 << shift)) - np.maximum(low, edge)

    def counts(self, box: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Object and query of each pair, and the pair's postings: a row for each threshold."""
        first, last, real = _ranges(self.space, self.level, box)
        whole = (box[2] - box[0]) * (box[3] - box[1])
        met = (whole[:, None] >= self.need[0]) & real[:, None] & self.real
        for k in (0, 1):
            met &= (first[k][:, None] <= self.last[k]) & (self.first[k] <= last[k][:, None])
        row, query = np.nonzero(met)
        out = np.zeros((len(self.need), len(row)), np.int64)
        many = (last[0] - first[0] + 1) * (last[1] - first[1] + 1)
        alone = many[row] > ALONE
        self._together(box, first, last, row, query, np.flatnonzero(~alone), out)
        big = np.flatnonzero(alone)
        for some in np.split(big, np.flatnonzero(np.diff(row[big])) + 1):
            if len(some):
                self._single([b[row[some[0]]] for b in box], [f[row[some[0]]] for f in first], [v[row[some[0]]] for v in last], query[some], some, out)
        return row, query, out

    def _upto(self, place: np.ndarray, before: np.ndarray, begin, end, left: np.ndarray) -> np.ndarray:
        """The place of the last posting whose bound is high enough, -1 without one. ``before`` is the weight of all postings before each, ``left`` what may be before."""
        at = np.searchsorted(before, left, "right") - 1
        return np.where(at >= begin, place[np.minimum(at, end - 1)], -1)

    def _ordered(self, box, first, last) -> tuple[np.ndarray, np.ndarray]:
        """Places of one rectangle's cells in their order, and the areas it covers of them."""
        own = self.place[first[1] : last[1] + 1, first[0] : last[0] + 1].ravel()
        w = [self._sides(k, np.arange(first[k], last[k] + 1), box[k], box[k + 2]) for k in (0, 1)]
        order = np.argsort(own)
        return own[order], (w[1][:, None] * w[0]).ravel()[order]

    def _single(self, box, first, last, query, some, out) -> None:
        own, weight = self._ordered(box, first, last)
        upto = np.cumsum(weight)
        cut = np.minimum(self._upto(own, upto - weight, 0, len(own), upto[-1] - self.need[:, query]), self.cut[:, query])
        for j, n in enumerate(query):
            a, b = (np.maximum(first, [self.first[0][n], self.first[1][n]]), np.minimum(last, [self.last[0][n], self.last[1][n]]))
            both = self.place[a[1] : b[1] + 1, a[0] : b[0] + 1]
            for k in range(len(cut)):
                if cut[k, j] < 0:
                    break
                out[k, some[j]] = np.count_nonzero(both <= cut[k, j])

    def _together(self, box, first, last, row, query, pairs, out) -> None:
        if not len(pairs):
            return
        rows, at = np.unique(row[pairs], return_inverse=True)
        r, x, y, begin = _unrolled([f[rows] for f in first], [v[rows] for v in last])
        place = self.place[y, x].astype(np.int64)
        w = self._sides(0, x, box[0][rows][r], box[2][rows][r]) * self._sides(1, y, box[1][rows][r], box[3][rows][r])
        order = np.argsort((r << 32) | place)
        place, w = place[order], w[order]
        upto = np.cumsum(w)
        cut = np.minimum(self._upto(place, upto - w, begin[at], begin[at + 1], upto[begin[at + 1] - 1] - self.need[:, query[pairs]]), self.cut[:, query[pairs]])
        use = cut[0] >= 0
        pairs, cut = pairs[use], cut[:, use]
        a = [np.maximum(first[k][row[pairs]], self.first[k][query[pairs]]) for k in (0, 1)]
        b = [np.minimum(last[k][row[pairs]], self.last[k][query[pairs]]) for k in (0, 1)]
        for some in _pieces((b[0] - a[0] + 1) * (b[1] - a[1] + 1), HELD):
            p, x, y, begin = _unrolled([v[some] for v in a], [v[some] for v in b])
            place = self.place[y, x]
            for k in range(len(cut)):
                upto = np.append(0, np.cumsum(place <= cut[k, some][p]))
                out[k, pairs[some]] = upto[begin[1:]] - upto[begin[:-1]]


class TokenSide:
    """The tokens: for a batch of objects, the postings of each query and object under each threshold."""

    def __init__(self, tokens: list[str], weights: np.ndarray, prefixes: list[tuple[np.ndarray, list[int]]], need: np.ndarray):
        """``tokens`` are in their order; a prefix has places of tokens, and how many of them each threshold leaves."""
        self.tokens, self.weights, self.need = tokens, weights, need
        self.wanted = np.unique(np.concatenate([p for p, _ in prefixes])) if prefixes else np.zeros(0, np.int64)
        self.prefixes = [(np.searchsorted(self.wanted, p), n) for p, n in prefixes]
        self.column = np.full(len(tokens), -1, np.int64)
        self.column[self.wanted] = np.arange(len(self.wanted))

    def bounds(self, row: np.ndarray, token: np.ndarray, n: int) -> np.ndarray:
        """Wanted tokens by objects, from the objects' tokens (places, -1 for one that isn't known): the bound of the posting, -1 without one."""
        row, token = row[token >= 0], token[token >= 0].astype(np.int64)
        order = np.argsort(row * len(self.tokens) + token)
        row, token = row[order], token[order]
        w = self.weights[token]
        upto = np.cumsum(w)
        total = np.append(0, upto)[np.searchsorted(row, np.arange(n), "right")]
        use = self.column[token] >= 0
        bound = np.full((len(self.wanted), n), -1, np.int64)
        bound[self.column[token[use]], row[use]] = (total[row] - upto + w)[use]
        return bound

    def counts(self, row: np.ndarray, token: np.ndarray, n: int) -> np.ndarray:
        """Thresholds by queries by objects: their postings."""
        bound = self.bounds(row, token, n)
        out = np.zeros((len(self.need), len(self.prefixes), n), np.int32)
        for j, (columns, many) in enumerate(self.prefixes):
            own = bound[columns]
            for k, m in enumerate(many):
                if m:
                    out[k, j] = np.count_nonzero(own[:m] >= self.need[k, j], axis=0)
        return out


def _columns(batch: pa.RecordBatch) -> tuple[list[np.ndarray], np.ndarray, pa.Array]:
    """Sides, numbers of tokens and all tokens of a batch of objects."""
    sides = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(4)]
    lengths = pc.fill_null(pc.list_value_length(batch.column(4)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    return sides, lengths, batch.column(4).flatten().cast(pa.string())


def token_cells(objects: DataFrame, space: Space, max_level: int) -> DataFrame:
    """token, level, cell, n_obj and covered (the sum of the areas that its objects cover) down to ``max_level``. Tasks sum up what they have; no row is made for an object's token and cell."""
    first_of = [(4**v - 1) // 3 for v in range(max_level + 2)]
    step = first_of[-1]

    def made(sides, lengths, flat):
        """Sums by token and cell, some HELD rows at a time. Areas are summed in two halves, which can't overflow."""
        begin = np.cumsum(lengths) - lengths
        for level in range(max_level + 1):
            first, last, real = _ranges(space, level, sides)
            rows = np.flatnonzero(real & (lengths > 0))
            first, last, box = [f[rows] for f in first], [v[rows] for v in last], [s[rows] for s in sides]
            for some in _pieces((last[0] - first[0] + 1) * (last[1] - first[1] + 1), HELD):
                r, x, y, _ = _unrolled([f[some] for f in first], [v[some] for v in last])
                w = np.ones(len(r), np.int64)
                for k, at in enumerate((x, y)):
                    edge = (space.x0, space.y0)[k] + (at << space.cell_bits(level)[k])
                    w *= np.minimum(box[k + 2][some][r], edge + (1 << space.cell_bits(level)[k])) - np.maximum(box[k][some][r], edge)
                cell, own = _code(x, y) + first_of[level], rows[some][r]
                for piece in _pieces(lengths[own], HELD):
                    many = lengths[own[piece]]
                    at = np.repeat(np.arange(len(many)), many)
                    token = flat[begin[own[piece]][at] + np.arange(len(at)) - np.repeat(np.cumsum(many) - many, many)]
                    at, token = at[token >= 0], token[token >= 0]
                    area = w[piece][at]
                    rows_ = pa.table({"key": token * step + cell[piece][at], "n": np.ones(len(at), np.int64), "high": area >> 24, "low": area & 0xFFFFFF})
                    yield _summed([rows_])

    def work(batches):
        names, held, total = pa.array([], pa.string()), [], 0

        def passed() -> pa.RecordBatch:
            sums = _summed(held)
            key = sums["key"].to_numpy()
            at = key % step
            level = np.searchsorted(first_of, at, "right") - 1
            token = names.take(pa.array(key // step))
            return pa.RecordBatch.from_arrays([token, pa.array(level.astype(np.int32)), pa.array(at - np.array(first_of)[level]), *[sums[c].combine_chunks() for c in ("n", "high", "low")]], names=["token", "level", "cell", "n", "high", "low"])

        for b in batches:
            sides, lengths, flat = _columns(b)
            names = pa.concat_arrays([names, flat.filter(pc.invert(pc.is_in(flat, value_set=names))).unique().drop_null()])
            for sums in made(sides, lengths, pc.fill_null(pc.index_in(flat, value_set=names), -1).to_numpy(zero_copy_only=False).astype(np.int64)):
                held.append(sums)
                total += len(sums)
                if total > HELD:
                    held = [_summed(held)]
                    total = len(held[0])
                    if total > HELD // 2:
                        yield passed()
                        held, total = [], 0
            if len(names) > VOCABULARY:
                if held:
                    yield passed()
                names, held, total = names[:0], [], 0
        if held:
            yield passed()

    parts = objects.select(*SIDES, "tokens").mapInArrow(work, "token string, level int, cell bigint, n bigint, high bigint, low bigint")
    return parts.groupBy("token", "level", "cell").agg(F.sum("n").alias("n_obj"), (F.sum("high") * (1 << 24) + F.sum("low")).alias("covered"))


def _summed(tables: list[pa.Table]) -> pa.Table:
    sums = pa.concat_tables(tables).group_by("key", use_threads=False).aggregate([(c, "sum") for c in ("n", "high", "low")])
    return sums.rename_columns([c.removesuffix("_sum") for c in sums.column_names])


def _overlaps(box: list[np.ndarray], cells: list[np.ndarray]) -> np.ndarray:
    """Shared areas, rectangles by cells."""
    wide, tall = (np.maximum(np.minimum(box[k + 2][:, None], cells[k + 2]) - np.maximum(box[k][:, None], cells[k]), 0) for k in (0, 1))
    return wide * tall


def _suffix_sums(w: np.ndarray) -> np.ndarray:
    return np.cumsum(w[:, ::-1], axis=1)[:, ::-1]


def _quad_side(ix: P.Index, q: DataFrame, batch: list, selection: DataFrame, setting: tuple[int, int] | None):
    """What tells, of some objects, how many postings a small batch retrieves by pairs of a token and one of its own cells, and which pairs of a query and an object; with the names of tokens and how many objects are told at once. None if the chosen cells of the batch's tokens are too many to be sent to tasks."""
    ids = [r.query_id for r in batch]
    tokens = _token_side(ix, q, ids, None if setting is None else [setting[1]], None if setting is None else setting[0])
    used = [columns[: many[0]] for columns, many in tokens.prefixes]
    spark = ix.objects.sparkSession
    asked = spark.createDataFrame([(tokens.tokens[tokens.wanted[c]],) for c in np.unique(np.concatenate([*used, np.zeros(0, np.int64)]))], "token string")
    rows = selection.join(F.broadcast(asked), "token", "left_semi").limit(HELD // 4 + 1).toArrow()
    if len(rows) > HELD // 4:
        return None
    at = pc.index_in(rows["token"], value_set=pa.array([tokens.tokens[w] for w in tokens.wanted], pa.string())).to_numpy()
    level, cell, n = (rows[c].to_numpy().astype(np.int64) for c in ("level", "cell", "n_obj"))
    order = np.lexsort((cell, n, level, at))
    at, level, cell = at[order], level[order], cell[order]
    bits = np.array([ix.space.cell_bits(v) for v in range(int(level.max(initial=0)) + 1)], np.int64)[level].reshape(-1, 2)
    low = [s + (c << bits[:, k]) for k, (s, c) in enumerate(zip((ix.space.x0, ix.space.y0), _place(cell), strict=True))]
    boxes = [*low, *[v + (np.int64(1) << bits[:, k]) for k, v in enumerate(low)]]
    ends = np.searchsorted(at, np.arange(len(tokens.wanted) + 1))
    cells = [[b[ends[c] : ends[c + 1]] for b in boxes] for c in range(len(tokens.wanted))]
    need_t = tokens.need[0]
    need_r = np.array([least_shared((r.x1 - r.x0) * (r.y1 - r.y0), r.tau_r_bp if setting is None else setting[0], ix.region_measure) for r in batch], np.int64)
    #: For each wanted token the queries that have it in their prefix, with the prefix of its cells.
    asking: list[list[tuple[int, np.ndarray]]] = [[] for _ in tokens.wanted]
    for j, (r, columns) in enumerate(zip(batch, used, strict=True)):
        for c in columns:
            w = _overlaps([np.array([r[s]], np.int64) for s in SIDES], cells[c])
            own = np.flatnonzero((w[0] > 0) & (_suffix_sums(w)[0] >= need_r[j]))
            if len(own):
                asking[c].append((j, own))
    rows = max(1, min(ROWS, HELD // max(1, len(tokens.wanted), len(ids))))

    def counted(box, lengths, flat) -> tuple[int, np.ndarray]:
        bound = tokens.bounds(np.repeat(np.arange(len(lengths)), lengths), flat, len(lengths))
        whole = (box[2] - box[0]) * (box[3] - box[1])
        seen, total = np.zeros((len(ids), len(lengths)), bool), 0
        for c, queries in enumerate(asking):
            if not queries:
                continue
            js = [j for j, _ in queries]
            all_ = np.flatnonzero((bound[c] >= need_t[js].min()) & (whole >= need_r[js].min()))
            for a in range(0, len(all_), most := max(1, HELD // len(cells[c][0]))):
                some = all_[a : a + most]
                w = _overlaps([b[some] for b in box], cells[c])
                use = np.where(w > 0, _suffix_sums(w), -1)
                for j, own in queries:
                    near = np.flatnonzero((bound[c, some] >= need_t[j]) & (whole[some] >= need_r[j]))
                    hits = np.count_nonzero(use[near[:, None], own] >= need_r[j], axis=1)
                    total += int(hits.sum())
                    seen[j, some[near[hits > 0]]] = True
        return total, seen

    return counted, tokens.tokens, rows


def quad_retrieved(ix: P.Index, q: DataFrame, selection: DataFrame, setting: tuple[int, int]) -> DataFrame | None:
    """retrieved and candidates of a small batch by pairs of a token and one of its own cells, under one setting; None if the chosen cells of the batch's tokens are too many to be sent to tasks."""
    side = _quad_side(ix, q, q.collect(), selection, setting)
    if side is None:
        return None
    counted, known, rows = side

    def work(batches):
        names = pa.array(known, pa.string())
        sums = np.zeros(2, np.int64)
        for b in batches:
            sides, lengths, words = _columns(b)
            flat = pc.fill_null(pc.index_in(words, value_set=names), -1).to_numpy(zero_copy_only=False)
            ends = np.append(0, np.cumsum(lengths))
            for a in range(0, b.num_rows, rows):
                e = min(a + rows, b.num_rows)
                total, seen = counted([s[a:e] for s in sides], lengths[a:e], flat[ends[a] : ends[e]])
                sums += np.array((total, np.count_nonzero(seen)), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(sums[:1]), pa.array(sums[1:])], names=["retrieved", "candidates"])

    parts = ix.objects.select(*SIDES, "tokens").mapInArrow(work, "retrieved bigint, candidates bigint")
    zero = F.lit(0).cast("bigint")
    return parts.agg(F.coalesce(F.sum("retrieved"), zero).alias("retrieved"), F.coalesce(F.sum("candidates"), zero).alias("candidates"))


def _token_side(ix: P.Index, q: DataFrame, ids: list[int], steps: list[int] | None, tau_r_bp: int | None) -> TokenSide:
    """With no steps, each query has its own threshold."""
    known = sorted(((r.n_obj, r.token.encode(), r.token, r.w) for r in ix.stats.select("token", "n_obj", "w").collect()))
    at = {r[2]: k for k, r in enumerate(known)}
    rows = {i: [] for i in ids}
    for r in P.token_prefix(ix, q if steps is None else with_thresholds(q, tau_r_bp, steps[0])).select("query_id", "token", "rest").collect():
        rows[r.query_id].append((at[r.token], r.rest))
    totals = {r.query_id: (r.w_total, r.tau_t_bp) for r in ix.prepared(q).select("query_id", "w_total", "tau_t_bp").collect()}
    need = np.array([[least_shared(totals[i][0], totals[i][1] if v is None else v, ix.measure) for i in ids] for v in steps or [None]], np.int64).reshape(len(steps or [None]), len(ids))
    prefixes = [(np.array([p for p, _ in sorted(rows[i])], np.int64), [sum(rest >= need[k, j] for _, rest in rows[i]) for k in range(len(need))]) for j, i in enumerate(ids)]
    return TokenSide([r[2] for r in known], np.array([r[3] for r in known], np.int64), prefixes, need)


def _grid_sides(ix: P.Index, batch: list, levels: list[int], steps: list[int] | None) -> list[GridSide]:
    box = [np.array([r[s] for r in batch], np.int64) for s in SIDES]
    need = np.array([[least_shared((r.x1 - r.x0) * (r.y1 - r.y0), r.tau_r_bp if v is None else v, ix.region_measure) for r in batch] for v in steps or [None]], np.int64).reshape(len(steps or [None]), len(batch))
    return [GridSide(ix.space, v, places(v, ix.cell_counts(v)), box, need) for v in levels]


def retrieved(ix: P.Index, q: DataFrame, methods: tuple[str, ...], levels: list[int], settings: tuple[tuple[int, int], ...]) -> DataFrame:
    """method, level, tau_r_bp, tau_t_bp, retrieved and candidates of a small batch, for ``token`` (level -1), ``grid`` and ``pair`` without a bucket limit, under each setting. A pair retrieves every token posting with every cell posting."""
    rs, ts = sorted({r for r, _ in settings}), sorted({t for _, t in settings})
    where = [(rs.index(r), ts.index(t)) for r, t in settings]
    batch = q.collect()
    ids = [r.query_id for r in batch]
    tokens = _token_side(ix, q, ids, ts, rs[0]) if {"token", "pair"} & set(methods) else None
    grids = _grid_sides(ix, batch, levels, rs) if {"grid", "pair"} & set(methods) else []
    made = [(m, v) for m in methods for v in ([-1] if m == "token" else levels)]
    rows = ROWS if tokens is None else max(1, min(ROWS, HELD // max(1, len(tokens.wanted), len(ts) * len(ids))))

    def counted(box, lengths, flat, sums) -> None:
        found = [g.counts(box) for g in grids]
        if tokens is not None:
            # Without the token filter, tokens matter only where cells meet.
            some = np.arange(len(lengths)) if "token" in methods else np.unique(np.concatenate([f[0] for f in found]))
            place = np.full(len(lengths), -1, np.int64)
            place[some] = np.arange(len(some))
            row = np.repeat(place, lengths)
            words = tokens.counts(row[row >= 0], flat[row >= 0], len(some))
        for j, (method, level) in enumerate(made):
            if method == "token":
                each = [(int(w.sum()), np.count_nonzero(w)) for w in words]
                each = [each[t] for _, t in where]
            else:
                r, query, cells = found[levels.index(level)]
                if method == "grid":
                    each = [(int(c.sum()), np.count_nonzero(c)) for c in cells]
                    each = [each[k] for k, _ in where]
                else:
                    both = [cells[k] * words[t][query, place[r]] for k, t in where]
                    each = [(int(c.sum()), np.count_nonzero(c)) for c in both]
            sums[j] += np.array(each, np.int64)

    def work(batches):
        sums = np.zeros((len(made), len(where), 2), np.int64)
        names = pa.array(tokens.tokens, pa.string()) if tokens is not None else None
        for b in batches:
            sides = [b.column(k).to_numpy(zero_copy_only=False) for k in range(4)]
            lengths, flat = np.zeros(b.num_rows, np.int64), np.zeros(0, np.int64)
            if tokens is not None:
                lengths = pc.fill_null(pc.list_value_length(b.column(4)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
                flat = pc.fill_null(pc.index_in(b.column(4).flatten().cast(pa.string()), value_set=names), -1).to_numpy(zero_copy_only=False)
            ends = np.append(0, np.cumsum(lengths))
            for a in range(0, b.num_rows, rows):
                e = min(a + rows, b.num_rows)
                counted([s[a:e] for s in sides], lengths[a:e], flat[ends[a] : ends[e]], sums)
        at = np.arange(len(made) * len(where))
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(sums[..., 0].ravel()), pa.array(sums[..., 1].ravel())], names=["at", "retrieved", "candidates"])

    columns = [*SIDES] + (["tokens"] if tokens is not None else [])
    parts = ix.objects.select(*columns).mapInArrow(work, "at bigint, retrieved bigint, candidates bigint")
    names = F.array(*[F.struct(F.lit(m).alias("method"), F.lit(v).alias("level"), F.lit(r).alias("tau_r_bp"), F.lit(t).alias("tau_t_bp")) for m, v in made for r, t in settings])
    # A table without files has no tasks, but each setting has its row.
    none = parts.sparkSession.range(len(made) * len(where)).select(F.col("id").alias("at"), F.lit(0).cast("bigint").alias("retrieved"), F.lit(0).cast("bigint").alias("candidates"))
    sums = parts.unionByName(none).groupBy("at").agg(F.sum("retrieved").alias("retrieved"), F.sum("candidates").alias("candidates"))
    return sums.select(F.element_at(names, (F.col("at") + 1).cast("int")).alias("s"), "retrieved", "candidates").select("s.*", "retrieved", "candidates")


def _reach(shared: np.ndarray, both: np.ndarray, bp: np.ndarray, measure: str) -> np.ndarray:
    """at_least for thresholds above 0, from what two share and the sum of their totals."""
    if measure == "dice":
        return (both > 0) & (2 * UNIT * shared >= bp * both)
    return (both > shared) & (UNIT * shared >= bp * (both - shared))


def sums_fit(ix: P.Index, q: DataFrame) -> bool:
    """Whether words are summed inside tasks: a small batch, thresholds above 0, few tokens, and measures that 64-bit integers can test."""
    if "cosine" in (ix.measure, ix.region_measure) or not P.is_small(q):
        return False
    low = q.agg(F.min("tau_r_bp"), F.min("tau_t_bp")).first()
    return None not in low and min(low) > 0 and ix.stats.limit(VOCABULARY + 1).count() <= VOCABULARY


def word_first_pairs(ix: P.Index, q: DataFrame) -> DataFrame:
    """query_id, object_id whose words are similar, and of these the ones whose areas are. Tasks hold the batch's tokens as lists of queries with weights; all pairs that share a token are summed up and tested there, exactly, and only what passes both tests leaves."""
    batch = q.collect()
    known = {r.token: r.w for r in ix.stats.select("token", "w").collect()}
    names = list(known)
    at = {t: k for k, t in enumerate(names)}
    weights = np.array([known[t] for t in names], np.int64)
    totals = {r.query_id: r.w_total for r in ix.prepared(q).select("query_id", "w_total").collect()}
    # A sweep has the same words over and over.
    lists: dict[tuple[int, ...], list[int]] = {}
    for j, r in enumerate(batch):
        lists.setdefault(tuple(sorted(at[t] for t in r.tokens or () if t in at)), []).append(j)
    lists.pop((), None)
    sets = [np.array(c, np.int64) for c in lists]
    asking = [np.array(js, np.int64) for js in lists.values()]
    wanted = np.unique(np.concatenate([*sets, np.zeros(0, np.int64)]))
    column = np.full(len(names) + 1, -1, np.int64)
    column[wanted] = np.arange(len(wanted))
    ids = np.array([r.query_id for r in batch], np.int64)
    total = np.array([totals[i] for i in ids.tolist()], np.int64)
    tau_r, tau_t = (np.array([r[c] for r in batch], np.int64) for c in ("tau_r_bp", "tau_t_bp"))
    sides = [np.array([r[c] for r in batch], np.int64) for c in SIDES]
    areas = (sides[2] - sides[0]) * (sides[3] - sides[1])
    rows = max(1, min(ROWS, HELD // max(1, len(sets), len(wanted))))
    #: Sets of words whose sums are made at once.
    group = 256
    measure, region = ix.measure, ix.region_measure

    def found(box, row, token, n):
        own = np.bincount(row, weights=weights[token], minlength=n).astype(np.int64)
        use = column[token] >= 0
        row, token = row[use], column[token[use]]
        whole = (box[2] - box[0]) * (box[3] - box[1])
        for a in range(0, len(sets), group):
            columns = np.unique(np.concatenate([column[c] for c in sets[a : a + group]]))
            place = np.full(len(wanted), -1, np.int64)
            place[columns] = np.arange(len(columns))
            has, lists_ = np.zeros((n, len(columns))), np.zeros((len(columns), len(sets[a : a + group])))
            here = place[token] >= 0
            np.add.at(has, (row[here], place[token[here]]), 1)
            for k, c in enumerate(sets[a : a + group]):
                lists_[place[column[c]], k] = weights[c]
            # Sums of integers below 2**53, which doubles hold exactly.
            shared = (has @ lists_).T.astype(np.int64)
            for k, js in enumerate(asking[a : a + group]):
                for j in js:
                    near = np.flatnonzero(_reach(shared[k], own + total[j], tau_t[j], measure))
                    for s in (0, 1):
                        near = near[(box[s][near] < sides[s + 2][j]) & (box[s + 2][near] > sides[s][j])]
                    wide, tall = (np.minimum(box[s + 2][near], sides[s + 2][j]) - np.maximum(box[s][near], sides[s][j]) for s in (0, 1))
                    near = near[_reach(np.maximum(wide, 0) * np.maximum(tall, 0), whole[near] + areas[j], tau_r[j], region)]
                    if len(near):
                        yield j, near

    def work(batches):
        words = pa.array(names, pa.string())
        for b in batches:
            box, lengths, flat = _columns(b)
            key = b.column(5).to_numpy(zero_copy_only=False)
            token = pc.fill_null(pc.index_in(flat, value_set=words), -1).to_numpy(zero_copy_only=False)
            ends = np.append(0, np.cumsum(lengths))
            for a in range(0, b.num_rows, rows):
                e = min(a + rows, b.num_rows)
                row, own = np.repeat(np.arange(e - a), lengths[a:e]), token[ends[a] : ends[e]]
                for j, near in found([s[a:e] for s in box], row[own >= 0], own[own >= 0], e - a):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(near), ids[j])), pa.array(key[a:e][near])], names=["query_id", "object_id"])

    return ix.objects.select(*SIDES, "tokens", "object_id").mapInArrow(work, "query_id bigint, object_id bigint")


def _pairs(ix: P.Index, batch: list, known: list[str] | None, rows: int, found, tested: bool) -> DataFrame:
    """query_id, object_id of what ``found`` tells of some objects (rows and queries of pairs); ``tested`` leaves only pairs whose areas are similar, which verify asks first."""
    ids = np.array([r.query_id for r in batch], np.int64)
    sides = [np.array([r[c] for r in batch], np.int64) for c in SIDES]
    tau, areas, region = np.array([r.tau_r_bp for r in batch], np.int64), (sides[2] - sides[0]) * (sides[3] - sides[1]), ix.region_measure

    def work(batches):
        names = None if known is None else pa.array(known, pa.string())
        for b in batches:
            key, box = b.column(0).to_numpy(zero_copy_only=False), [b.column(k).to_numpy(zero_copy_only=False) for k in range(1, 5)]
            lengths, flat = np.zeros(b.num_rows, np.int64), np.zeros(0, np.int64)
            if names is not None:
                lengths = pc.fill_null(pc.list_value_length(b.column(5)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
                flat = pc.fill_null(pc.index_in(b.column(5).flatten().cast(pa.string()), value_set=names), -1).to_numpy(zero_copy_only=False)
            ends = np.append(0, np.cumsum(lengths))
            for a in range(0, b.num_rows, rows):
                e = min(a + rows, b.num_rows)
                own = [s[a:e] for s in box]
                row, query = found(own, lengths[a:e], flat[ends[a] : ends[e]])
                if tested:
                    wide, tall = (np.minimum(own[k + 2][row], sides[k + 2][query]) - np.maximum(own[k][row], sides[k][query]) for k in (0, 1))
                    whole = (own[2] - own[0]) * (own[3] - own[1])
                    near = _reach(np.maximum(wide, 0) * np.maximum(tall, 0), whole[row] + areas[query], tau[query], region)
                    row, query = row[near], query[near]
                yield pa.RecordBatch.from_arrays([pa.array(ids[query]), pa.array(key[a:e][row])], names=["query_id", "object_id"])

    return ix.objects.select("object_id", *SIDES, *([] if known is None else ["tokens"])).mapInArrow(work, "query_id bigint, object_id bigint")


def probed(ix: P.Index, q: DataFrame, level: int, method: str, tested: bool = False) -> DataFrame:
    """Candidates of ``two_filter`` or of ``pair`` without a bucket limit, each query at its own thresholds: postings are counted as in ``retrieved``, and pairs that retrieve some leave the task."""
    batch = q.collect()
    tokens, (grid,) = _token_side(ix, q, [r.query_id for r in batch], None, None), _grid_sides(ix, batch, [level], None)
    rows = max(1, min(ROWS, HELD // max(1, len(tokens.wanted), len(batch))))

    def found(box, lengths, flat):
        row, query, cells = grid.counts(box)
        met = cells[0] > 0
        row, query, cells = row[met], query[met], cells[0][met]
        some = np.unique(row)
        place = np.full(len(lengths), -1, np.int64)
        place[some] = np.arange(len(some))
        at = np.repeat(place, lengths)
        words = tokens.counts(at[at >= 0], flat[at >= 0], len(some))[0][query, place[row]]
        use = cells * words > 0 if method == "pair" else words > 0
        return row[use], query[use]

    return _pairs(ix, batch, tokens.tokens, rows, found, tested)


def quad_probed(ix: P.Index, q: DataFrame, selection: DataFrame, tested: bool = False) -> DataFrame | None:
    """Candidates by pairs of a token and one of its own cells, each query at its own thresholds; None if the cells are too many to be sent to tasks."""
    batch = q.collect()
    side = _quad_side(ix, q, batch, selection, None)
    if side is None:
        return None
    counted, known, rows = side

    def found(box, lengths, flat):
        return np.nonzero(counted(box, lengths, flat)[1])[::-1]

    return _pairs(ix, batch, known, rows, found, tested)


def met_areas(ix: P.Index, q: DataFrame, level: int) -> DataFrame:
    """Pairs that share a cell of a level and whose areas are similar."""
    batch = q.collect()
    space, sides = ix.space, [np.array([r[c] for r in batch], np.int64) for c in SIDES]
    low, high, real = _ranges(space, level, sides)

    def found(box, lengths, flat):
        first, last, has = _ranges(space, level, box)
        met = has[:, None] & real
        for k in (0, 1):
            met &= (first[k][:, None] <= high[k]) & (low[k] <= last[k][:, None])
        return np.nonzero(met)

    return _pairs(ix, batch, None, max(1, min(ROWS, HELD // max(1, len(batch)))), found, True)
