"""The experiments as tables: one row for each setting, with costs in counts that don't depend on the machine."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arealex.functions.similarity import at_least, shared_enough
from arealex.operators import counting as C
from arealex.operators import probes as P
from arealex.operators import quadcells as Q
from arealex.operators.verify import verify
from arealex.plans import measures as M
from arealex.plans import search as X
from arealex.sources.querysets import query_set, with_thresholds
from arealex.sources.shared import kept

#: Thresholds of the sweeps, in basis points; the default of the other side.
SWEEP, DEFAULT = (1000, 2000, 3000, 4000, 5000), 4000


#: Both sweeps: one threshold moves, the other keeps its default.
SETTINGS = tuple(dict.fromkeys([(r, DEFAULT) for r in SWEEP] + [(DEFAULT, t) for t in SWEEP]))


def _row(hits: DataFrame, **labels) -> DataFrame:
    """Postings retrieved and candidates of one setting."""
    counts = hits.agg(F.count("*").alias("retrieved"), F.count_distinct("query_id", "object_id").alias("candidates"))
    return counts.select(*[F.lit(v).alias(k) for k, v in labels.items()], "retrieved", "candidates")


def _table(rows: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, rows)


def swept(q: DataFrame, settings: tuple[tuple[int, int], ...]) -> DataFrame:
    """One batch of all queries under all settings, so a sweep is one probe: a query's number is multiplied and the place of the setting added."""
    places = F.explode(F.array(*[F.struct(F.lit(k).cast("bigint").alias("k"), F.lit(r).cast("bigint").alias("r"), F.lit(t).cast("bigint").alias("t")) for k, (r, t) in enumerate(settings)]))
    rows = q.withColumn("s", places).withColumn("query_id", F.col("query_id") * len(settings) + F.col("s.k"))
    return P.known_size(rows.withColumn("tau_r_bp", F.col("s.r")).withColumn("tau_t_bp", F.col("s.t")).drop("s"))


def _lowest(ix: P.Index, settings: tuple[tuple[int, int], ...]) -> dict[tuple[int, int], tuple[int, int]]:
    """For each setting one of no higher thresholds whose answers hold all of its own: the least of its sweep. Cosine isn't told from what is shared and the union, so each setting then is its own."""
    if "cosine" in (ix.measure, ix.region_measure):
        return {s: s for s in settings}
    return {(r, t): (min(a for a, b in settings if b == t), t) if t == DEFAULT else (r, min(b for a, b in settings if a == r)) for r, t in settings}


def _by_setting(ix: P.Index, found: DataFrame, lowest: dict[tuple[int, int], tuple[int, int]], asked: tuple[tuple[int, int], ...]) -> DataFrame:
    """Answers of a swept batch under each setting that they hold for."""
    if asked == tuple(lowest):
        holds = lambda s: F.lit(True)
    else:
        holds = lambda s: at_least(F.col("inter_area"), F.col("union_area"), F.col("inter_area"), s["tau_r_bp"], ix.region_measure) & at_least(F.col("inter_w"), F.col("union_w"), F.col("inter_w"), s["tau_t_bp"], ix.measure)
    every = F.array(*[F.struct(F.lit(asked.index(low)).alias("k"), F.lit(r).alias("tau_r_bp"), F.lit(t).alias("tau_t_bp")) for (r, t), low in lowest.items()])
    own = F.filter(every, lambda s: (s["k"] == F.pmod("query_id", F.lit(len(asked)))) & holds(s))
    return found.select("inter_area", "inter_w", F.inline(own)).drop("k")


def _token_counts(ix: P.Index, q: DataFrame, steps: list[int]) -> DataFrame:
    """Pairs with the postings t0, t1, ... that the token filter retrieves at each threshold, by one probe at the least: what is retrieved at a threshold is at all lower ones."""
    hits = P.token_bounded_hits(ix, with_thresholds(q, DEFAULT, min(steps)))
    holds = lambda v: shared_enough(F.least("rest", "bound_t"), F.col("w_total"), F.lit(v), ix.measure)
    return hits.groupBy("query_id", "object_id").agg(*[F.sum(holds(v).cast("bigint")).alias(f"t{k}") for k, v in enumerate(steps)])


def _grid_counts(ix: P.Index, q: DataFrame, level: int, steps: list[int]) -> DataFrame:
    """The same of the grid filter: g0, g1, ..."""
    hits = P.grid_bounded_hits(ix, with_thresholds(q, min(steps), DEFAULT), level)
    holds = lambda v: shared_enough(F.least("rest", "bound_r"), F.col("area"), F.lit(v), ix.region_measure)
    return hits.groupBy("query_id", "object_id").agg(*[F.sum(holds(v).cast("bigint")).alias(f"g{k}") for k, v in enumerate(steps)])


def _setting_rows(pairs: DataFrame, retrieved: dict[tuple[int, int], Column], **labels) -> DataFrame:
    """Postings retrieved and candidates of each setting, from a pair's postings under it; a setting that retrieves nothing has no row."""
    sums = pairs.agg(*[f(c).alias(f"{n}{k}") for k, c in enumerate(retrieved.values()) for n, f in (("r", F.sum), ("c", lambda c: F.sum((c > 0).cast("bigint"))))])
    rows = [F.struct(*[F.lit(v).alias(n) for n, v in (*labels.items(), ("tau_r_bp", r), ("tau_t_bp", t))], F.col(f"r{k}").alias("retrieved"), F.col(f"c{k}").alias("candidates")) for k, (r, t) in enumerate(retrieved)]
    return sums.select(F.inline(F.array(*rows))).where("retrieved > 0")


def token_or_grid(ix: P.Index, kind: str, levels: list[int], settings: tuple[tuple[int, int], ...] = SETTINGS) -> DataFrame:
    """Token against grid filter over both sweeps of thresholds; the token filter has level -1."""
    q, rs, ts = query_set(ix, kind, DEFAULT, DEFAULT), sorted({r for r, _ in settings}), sorted({t for _, t in settings})
    if C.fits(ix, q, levels):
        return C.retrieved(ix, q, ("token", "grid"), levels, settings).where("retrieved > 0")
    rows = [_setting_rows(_token_counts(ix, q, ts), {s: F.col(f"t{ts.index(s[1])}") for s in settings}, method="token", level=-1)]
    return _table(rows + [_setting_rows(_grid_counts(ix, q, v, rs), {s: F.col(f"g{rs.index(s[0])}") for s in settings}, method="grid", level=v) for v in levels])


def granularity(ix: P.Index, kind: str, levels: list[int]) -> DataFrame:
    """The grid filter at each level: candidates fall and postings rise with it."""
    q = query_set(ix, kind, DEFAULT, DEFAULT)
    if C.fits(ix, q, levels):
        return C.retrieved(ix, q, ("grid",), levels, ((DEFAULT, DEFAULT),)).select("level", "retrieved", "candidates")
    return _table([_row(P.grid_bounded_hits(ix, q, v), level=v) for v in levels])


def grid_or_pair(ix: P.Index, kind: str, levels: list[int], settings: tuple[tuple[int, int], ...] = SETTINGS) -> DataFrame:
    """Grid against pair filter at the same levels, over both sweeps. Without a bucket limit the pair probe retrieves every token posting with every cell posting of a pair, so their counts are multiplied and the pairs of postings not made."""
    q, rs, ts = query_set(ix, kind, DEFAULT, DEFAULT), sorted({r for r, _ in settings}), sorted({t for _, t in settings})
    if C.fits(ix, q, levels):
        return C.retrieved(ix, q, ("grid", "pair"), levels, settings).where("retrieved > 0")
    tokens, rows = kept(_token_counts(ix, q, ts)), []
    for v in levels:
        cells = kept(_grid_counts(ix, q, v, rs))
        rows.append(_setting_rows(cells, {s: F.col(f"g{rs.index(s[0])}") for s in settings}, method="grid", level=v))
        rows.append(_setting_rows(tokens.join(cells, ["query_id", "object_id"]), {s: F.col(f"t{ts.index(s[1])}") * F.col(f"g{rs.index(s[0])}") for s in settings}, method="pair", level=v))
    return _table(rows)


def pair_or_quad(ix: P.Index, kind: str, levels: list[int], budgets: list[int], max_level: int, modes: tuple[str, ...] = ("children", "children_weighted"), tau_r_bp: int = 4000, tau_t_bp: int = 1000) -> DataFrame:
    """Pair against quadtree pair filter, with the size of each index."""
    q = query_set(ix, kind, tau_r_bp, tau_t_bp)
    rows = []
    for v in levels:
        size = M.index_size(ix, [v], budget=0).where(F.col("kind") == f"pair{v}").select(F.col("postings").alias("index_rows"))
        rows.append(_row(P.pair_hits(ix, q, v), method="pair", setting=v).crossJoin(size))
    for mode in modes:
        for b in budgets:
            selection = kept(Q.pick_quad_cells(ix, b, max_level, mode))
            size = Q.quad_postings(ix, selection, max_level).agg(F.count("*").alias("index_rows"))
            rows.append(_row(Q.quad_hits(ix, q, selection, max_level), method=f"quad_{mode}", setting=b).crossJoin(size))
    return _table(rows)


COMPARED = ("word_first", "area_first", "word_tree", "two_filter", "pair", "quad_pair")


def comparison(ix: P.Index, kind: str, settings: tuple[tuple[int, int], ...] = SETTINGS, methods: tuple[str, ...] = COMPARED) -> DataFrame:
    """Answers of each method over both sweeps: the same numbers for all. A method answers a sweep once, at its least threshold, and the answers are tested under each setting."""
    lowest = _lowest(ix, settings)
    asked = tuple(dict.fromkeys(lowest.values()))
    q = swept(query_set(ix, kind, DEFAULT, DEFAULT), asked)
    rows = [_by_setting(ix, X.search(ix, q, m), lowest, asked).groupBy("tau_r_bp", "tau_t_bp").agg(F.count("*").alias("answers"), F.sum("inter_area").alias("inter_area"), F.sum("inter_w").alias("inter_w")).select(F.lit(m).alias("method"), "*") for m in methods]
    return _table(rows)


def sweep_answers(ix: P.Index, kind: str, thresholds: list[tuple[int, int]]) -> DataFrame:
    """Answers for pairs of thresholds, rolled up as a cube; -1 stands for all thresholds of a side."""
    q = query_set(ix, kind, *thresholds[0])
    rows = _table([verify(ix, own, P.two_filter(ix, own, X.LEVEL)).select(F.lit(r).alias("tau_r_bp"), F.lit(t).alias("tau_t_bp"), "query_id") for r, t in thresholds for own in [with_thresholds(q, r, t)]])
    sums = rows.cube("tau_r_bp", "tau_t_bp").agg(F.count("*").alias("answers"), F.count_distinct("query_id").alias("queries"))
    return sums.na.fill(-1, ["tau_r_bp", "tau_t_bp"])


def part_of(objects: DataFrame, percent: int) -> DataFrame:
    """A repeatable share of the objects."""
    return objects.where(F.pmod(F.col("object_id") * 7919 + 13, F.lit(100)) < percent)


def scaling(objects: DataFrame, percents: list[int], kind: str = "large", method: str = "pair", level: int = X.LEVEL, budget: int = X.BUDGET, max_level: int = X.QUAD_LEVEL) -> DataFrame:
    """A filter on growing shares of the objects: pairs on a uniform grid, or on the cells chosen for each token."""
    rows = []
    for p in percents:
        ix = P.Index(part_of(objects, p))
        q = query_set(ix, kind, DEFAULT, DEFAULT)
        if method == "pair" and C.fits(ix, q, [level]):
            rows.append(C.retrieved(ix, q, ("pair",), [level], ((DEFAULT, DEFAULT),)).select(F.lit(p).alias("percent"), "retrieved", "candidates"))
            continue
        if method == "pair":
            rows.append(_row(P.pair_hits(P.Index(kept(ix.objects)), q, level), percent=p))
            continue
        selection = kept(Q.pick_quad_cells(ix, budget, max_level))
        counts = C.quad_retrieved(ix, q, selection, (DEFAULT, DEFAULT)) if C.fits(ix, q, [max_level]) else None
        rows.append(_row(Q.quad_hits(ix, q, selection, max_level), percent=p) if counts is None else counts.select(F.lit(p).alias("percent"), "retrieved", "candidates"))
    return _table(rows)
