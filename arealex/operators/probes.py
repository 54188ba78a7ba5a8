"""Filters: from a batch of queries to candidate pairs, none of which miss an answer.

``hits`` of a filter are the postings it retrieves; its candidates are their distinct pairs. A batch of up to BATCH_ROWS queries is collected once, so that the planner knows how small it is and broadcasts it; a larger one stays distributed and is joined by shuffles.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.cells import Space, bounding_space, cell_box, cell_range, cells_of
from arealex.functions.similarity import SIDES, area, box, overlap_area, shared_enough
from arealex.operators import signatures as S
from arealex.sources.shared import kept

BATCH_ROWS, BATCH_BYTES = 20_000, 16_000_000
#: An axis of the space may be this long (as a power of two), so that areas times 10,000 stay within BIGINT.
LONGEST_BITS = 24
QUERY_COLUMNS = ("query_id", *SIDES, "tokens", "tau_r_bp", "tau_t_bp")


def is_small(queries: DataFrame) -> bool:
    """Whether a batch has at most BATCH_ROWS rows and BATCH_BYTES of words."""
    size = F.aggregate("tokens", F.lit(0).cast("bigint"), lambda n, t: n + F.octet_length(t)) + 16 * F.size("tokens") if "tokens" in queries.columns else F.lit(64)
    n, total = queries.limit(BATCH_ROWS + 1).agg(F.count("*"), F.coalesce(F.sum(size), F.lit(0))).first()
    return n <= BATCH_ROWS and total <= BATCH_BYTES


def known_size(queries: DataFrame) -> DataFrame:
    """The batch as a local relation if it is small."""
    q = queries.select(*QUERY_COLUMNS)
    return q.sparkSession.createDataFrame(q.collect(), q.schema) if is_small(q) else q


def bounded(queries: DataFrame) -> DataFrame:
    """The batch, if it is small enough to be held against every object."""
    if not is_small(queries):
        raise ValueError(f"a scan takes at most {BATCH_ROWS} queries and {BATCH_BYTES} bytes of words at once")
    return queries


@dataclass
class Index:
    """What filters need of the objects. Weights and counts of cells are written once, other frames are lazy; ``space``, weights and orders are fixed by the objects that it was made of."""

    objects: DataFrame
    measure: str = "jaccard"
    region_measure: str = "jaccard"
    weighted: bool = True
    order: str = "rare"
    space: Space | None = None
    stats: DataFrame | None = None
    _made: dict = field(default_factory=dict)

    def __post_init__(self):
        self.space = self.space or bounding_space(self.objects)
        if self.space.x_bits + self.space.y_bits > 2 * LONGEST_BITS:
            raise ValueError("the space is larger than 2**48 units; scale the sides down (sources.objects.scaled takes negative decimals)")
        #: Whether the weights are of these objects, so that an object weighs at least what it shares.
        self.own_weights = self.stats is None
        self.stats = kept(S.token_stats(self.objects, self.weighted)) if self.stats is None else self.stats

    def _once(self, key, make):
        if key not in self._made:
            self._made[key] = make()
        return self._made[key]

    @property
    def full(self) -> DataFrame:
        return self._once("full", lambda: S.weighted_objects(self.objects, self.stats))

    @property
    def tokens(self) -> DataFrame:
        return self._once("tokens", lambda: S.token_postings(self.objects, self.stats, self.order))

    def cells(self, level: int) -> DataFrame:
        return self._once(("cells", level), lambda: S.cell_postings(self.objects, self.space, level, self.order, self.cell_counts(level)))

    def cell_counts(self, level: int) -> DataFrame:
        return self._once(("counts", level), lambda: kept(S.cell_counts(self.objects, self.space, level)))

    def within(self, objects: DataFrame, level: int) -> Index:
        """An index of some of the objects, with the weights, counts and space of all."""
        some = Index(objects, self.measure, self.region_measure, self.weighted, self.order, self.space, self.stats)
        some.own_weights = self.own_weights
        some._made |= {"count": self.count(), ("counts", level): self.cell_counts(level)}
        return some

    def count(self) -> int:
        return self._once("count", self.objects.count)

    def query_tokens(self, queries: DataFrame) -> DataFrame:
        """query_id, token, w, n_obj; a token of no object counts as one of a single object."""
        unseen = F.round(F.log(F.lit(float(max(1, self.count())))) * S.SCALE).cast("bigint") if self.weighted else F.lit(S.SCALE).cast("bigint")
        rows = queries.select("query_id", F.explode("tokens").alias("token")).join(self.stats, "token", "left")
        return rows.select("query_id", "token", F.coalesce("w", unseen).alias("w"), "n_obj")

    def prepared(self, queries: DataFrame) -> DataFrame:
        """The batch with area, w_total and weights (a map of its own tokens); a small batch stays a local relation."""
        # The batch is kept beside the result, so its id isn't given away again.
        return self._once(("prepared", id(queries)), lambda: (queries, self._prepared(queries)))[1]

    def _prepared(self, queries: DataFrame) -> DataFrame:
        w = self.query_tokens(queries).groupBy("query_id").agg(F.sum("w").alias("w_total"), F.map_from_entries(F.collect_list(F.struct("token", "w"))).alias("weights"))
        none = F.map_from_arrays(F.array().cast("array<string>"), F.array().cast("array<bigint>"))
        q = queries.join(w, "query_id", "left").withColumn("w_total", F.coalesce("w_total", F.lit(0).cast("bigint"))).withColumn("weights", F.coalesce("weights", none))
        q = q.withColumn("area", area(box()))
        return q.sparkSession.createDataFrame(q.collect(), q.schema) if is_small(queries) else q


def _enough_t(ix: Index, bound: str):
    return shared_enough(F.col(bound), F.col("w_total"), F.col("tau_t_bp"), ix.measure)


def _enough_r(ix: Index, bound: str):
    return shared_enough(F.col(bound), F.col("area"), F.col("tau_r_bp"), ix.region_measure)


def _totals(ix: Index, q: DataFrame) -> DataFrame:
    return ix.prepared(q).select("query_id", "area", "w_total", "tau_r_bp", "tau_t_bp")


def token_prefix(ix: Index, q: DataFrame, use_prefix: bool = True) -> DataFrame:
    """query_id, token and the query's totals: tokens that some object has, up to where the rest stays under the threshold."""
    sig = ix.query_tokens(q).where(F.col("n_obj").isNotNull())
    bounded = S.with_bound(sig, ["query_id"], S.element_order("token", ix.order), "rest").join(_totals(ix, q), "query_id")
    return bounded.where(_enough_t(ix, "rest")) if use_prefix else bounded


def cell_prefix(ix: Index, q: DataFrame, level: int, use_prefix: bool = True) -> DataFrame:
    """query_id, cell, w and the query's totals: cells that some object meets, up to where the rest stays under the threshold."""
    sig = cells_of(q, ix.space, level, "query_id").hint("merge").join(ix.cell_counts(level), "cell")
    bounded = S.with_bound(sig, ["query_id"], S.element_order("cell", ix.order), "rest").join(_totals(ix, q), "query_id")
    return bounded.where(_enough_r(ix, "rest")) if use_prefix else bounded


def pairs_of(hits: DataFrame) -> DataFrame:
    return hits.select("query_id", "object_id").distinct()


def near(ix: Index, q: DataFrame, level: int, use_bound: bool = True) -> Index:
    """The index of those objects that a small batch's grid probe can retrieve: their cells and some query's lie across each other, and the whole object covers enough. Bounds are made of these objects only, so what is shuffled follows the batch and not the objects. A large batch keeps all objects."""
    if ("cells", level) in ix._made or not is_small(q):
        return ix
    ranges = lambda: [c for axis, (low, high) in enumerate((("x0", "x1"), ("y0", "y1"))) for c in cell_range(ix.space, level, low, high, axis)]
    names = ("_ax", "_bx", "_ay", "_by")
    # A sweep has the same rectangles over and over.
    boxes = q.groupBy(*SIDES).agg(F.min("tau_r_bp").alias("tau_r_bp")).select(area(box()).alias("area"), "tau_r_bp", *[c.alias(f"q{n}") for c, n in zip(ranges(), names, strict=True)])
    own = ix.objects.select("*", area(box()).alias("_area"), *[c.alias(n) for c, n in zip(ranges(), names, strict=True)])
    met = (F.col("_ax") <= F.col("q_bx")) & (F.col("q_ax") <= F.col("_bx")) & (F.col("_ay") <= F.col("q_by")) & (F.col("q_ay") <= F.col("_by"))
    rows = own.join(F.broadcast(boxes), met & _enough_r(ix, "_area") if use_bound else met, "left_semi")
    return ix.within(kept(rows.select(*ix.objects.columns)), level)


def token_overlap_hits(ix: Index, q: DataFrame) -> DataFrame:
    return ix.query_tokens(q).join(ix.tokens.select("object_id", "token"), "token")


def token_overlap(ix: Index, q: DataFrame) -> DataFrame:
    """Pairs whose shared tokens weigh enough, with inter_w."""
    sums = token_overlap_hits(ix, q).groupBy("query_id", "object_id").agg(F.sum("w").alias("inter_w"))
    return sums.join(_totals(ix, q), "query_id").where(_enough_t(ix, "inter_w")).select("query_id", "object_id", "inter_w")


def grid_overlap_hits(ix: Index, q: DataFrame, level: int) -> DataFrame:
    own = cells_of(q, ix.space, level, "query_id").withColumnRenamed("w", "w_q")
    return own.join(S.grid_signature(ix.objects, ix.space, level), "cell")


def grid_overlap(ix: Index, q: DataFrame, level: int, cell_weight: str = "least") -> DataFrame:
    """Pairs for which the smaller covered areas of shared cells add up to enough, with that sum (an upper bound of the overlap). With cell_weight ``exact``, a cell counts with the area that query and object share in it, so the sum is the overlap: what bounds are measured against, as it needs all sides of all postings."""
    if cell_weight == "exact":
        own = cells_of(q, ix.space, level, "query_id", *SIDES).withColumnsRenamed({s: f"q_{s}" for s in SIDES}).drop("w")
        on = own.join(cells_of(ix.objects, ix.space, level, "object_id", *SIDES), "cell")
        both = tuple(F.greatest(f"q_{s}", s) if k < 2 else F.least(f"q_{s}", s) for k, s in enumerate(SIDES))
        sums = on.withColumn("shared", overlap_area(both, cell_box(ix.space, level))).groupBy("query_id", "object_id").agg(F.sum("shared").alias("shared")).where("shared > 0")
    else:
        sums = grid_overlap_hits(ix, q, level).groupBy("query_id", "object_id").agg(F.sum(F.least("w", "w_q")).alias("shared"))
    return sums.join(_totals(ix, q), "query_id").where(_enough_r(ix, "shared")).select("query_id", "object_id", "shared")


def token_bounded_hits(ix: Index, q: DataFrame, use_prefix: bool = True, use_bound: bool = True) -> DataFrame:
    p = token_prefix(ix, q, use_prefix).drop("w")
    on = ix.tokens.select("object_id", "token", "bound_t").join(p, "token")
    return on.where(_enough_t(ix, "bound_t")) if use_bound else on


def token_bounded(ix: Index, q: DataFrame, use_prefix: bool = True, use_bound: bool = True, recheck_sum: bool = False) -> DataFrame:
    """Pairs that meet under a token of the query's prefix at a posting whose bound is high enough. ``recheck_sum`` also asks for the summed test."""
    found = pairs_of(token_bounded_hits(ix, q, use_prefix, use_bound))
    return found.join(token_overlap(ix, q).select("query_id", "object_id"), ["query_id", "object_id"], "left_semi") if recheck_sum else found


def grid_bounded_hits(ix: Index, q: DataFrame, level: int, use_prefix: bool = True, use_bound: bool = True) -> DataFrame:
    p = cell_prefix(ix, q, level, use_prefix).select("query_id", "cell", "area", "tau_r_bp", "rest")
    some = near(ix, q, level, use_bound)
    if some.order == "rare" and level <= S.DENSE_LEVEL and ("cells", level) not in some._made and is_small(q):
        p = kept(p)
        lists = S.bounded_cells(some.objects, ix.space, level, some.cell_counts(level), p)
    else:
        lists = some.cells(level).select("object_id", "cell", "bound_r")
    on = lists.hint("merge").join(p, "cell")
    return on.where(_enough_r(ix, "bound_r")) if use_bound else on


def grid_bounded(ix: Index, q: DataFrame, level: int, use_prefix: bool = True, use_bound: bool = True, recheck_sum: bool = False) -> DataFrame:
    """The same on the cells of one level."""
    found = pairs_of(grid_bounded_hits(ix, q, level, use_prefix, use_bound))
    return found.join(grid_overlap(ix, q, level).select("query_id", "object_id"), ["query_id", "object_id"], "left_semi") if recheck_sum else found


def two_filter(ix: Index, q: DataFrame, level: int, tested: bool = False) -> DataFrame:
    """Candidates of both bounded probes: the grid's pairs, which are fewer, cut the token postings before these are made distinct. A small batch is probed inside tasks, where ``tested`` may leave out pairs whose areas aren't similar."""
    from arealex.operators import counting as C  # which is made of this module

    if C.fits(ix, q, [level]):
        return C.probed(ix, q, level, "two_filter", tested and C.sums_fit(ix, q))
    some = near(ix, q, level)
    met = grid_bounded(some, q, level)
    return pairs_of(token_bounded_hits(some, q).select("query_id", "object_id").join(met, ["query_id", "object_id"], "left_semi"))


def pair_hits(ix: Index, q: DataFrame, level: int, buckets: int | None = None) -> DataFrame:
    """Postings under a prefix token and a prefix cell at once, with both bounds high enough.

    Without a bucket limit only tokens and cells of some query's prefix take part in the cross product of an object, which changes nothing in the result.
    """
    t = token_prefix(ix, q).select("query_id", "token", "w_total", "tau_t_bp")
    c = cell_prefix(ix, q, level).select("query_id", "cell", "area", "tau_r_bp")
    own = t.join(c, "query_id")
    if buckets is None:
        some = near(ix, q, level)
        tokens = some.tokens.join(t.select("token").distinct(), "token", "left_semi")
        cells = some.cells(level).hint("merge").join(c.select("cell").distinct(), "cell", "left_semi")
        on = S.pair_postings(tokens, cells, None).join(own, ["token", "cell"])
    else:
        own = own.withColumn("bucket", S.pair_bucket(F.col("token"), F.col("cell"), buckets)).drop("token", "cell").distinct()
        on = S.pair_postings(ix.tokens, ix.cells(level), buckets).join(own, "bucket")
    return on.where(_enough_t(ix, "bound_t") & _enough_r(ix, "bound_r"))


def pair(ix: Index, q: DataFrame, level: int, buckets: int | None = None, tested: bool = False) -> DataFrame:
    """Candidates by token-and-cell pairs; with no bucket limit they are those of two_filter, and a small batch's are found inside tasks."""
    from arealex.operators import counting as C  # which is made of this module

    if buckets is None and C.fits(ix, q, [level]):
        return C.probed(ix, q, level, "pair", tested and C.sums_fit(ix, q))
    return pairs_of(pair_hits(ix, q, level, buckets))


def signature_scan(ix: Index, q: DataFrame) -> DataFrame:
    """Enumerates each object's tokens for each query of a bounded batch, without an index."""
    w = ix.prepared(bounded(q)).select("query_id", "weights", "w_total", "tau_t_bp")
    shared = F.aggregate(F.filter("tokens", lambda t: F.map_contains_key("weights", t)), F.lit(0).cast("bigint"), lambda s, t: s + F.element_at("weights", t))
    rows = ix.objects.select("object_id", "tokens").crossJoin(F.broadcast(w))
    return rows.withColumn("inter_w", shared).where(_enough_t(ix, "inter_w")).select("query_id", "object_id")


def size_filter(ix: Index, q: DataFrame, candidates: DataFrame) -> DataFrame:
    """Of candidates, those whose totals are near enough to the query's for Jaccard: no smaller than tau times it, nor larger than it by tau."""
    p = _totals(ix, q).withColumnsRenamed({"w_total": "w_q", "area": "area_q"})
    o = ix.full.select("object_id", area(box()).alias("area_o"), F.col("w_total").alias("w_o"))
    j = candidates.join(p, "query_id").join(o, "object_id")
    ok = (10_000 * F.col("area_o") >= F.col("tau_r_bp") * F.col("area_q")) & (10_000 * F.col("area_q") >= F.col("tau_r_bp") * F.col("area_o"))
    ok = ok & (10_000 * F.col("w_o") >= F.col("tau_t_bp") * F.col("w_q")) & (10_000 * F.col("w_q") >= F.col("tau_t_bp") * F.col("w_o"))
    return j.where(ok).select("query_id", "object_id")
