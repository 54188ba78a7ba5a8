"""Search: filter, then verify."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.functions.similarity import SIDES, area, box
from arealex.operators import baselines as B
from arealex.operators import linking as K
from arealex.operators import probes as P
from arealex.operators import quadcells as Q
from arealex.operators.verify import exact_scan, verify
from arealex.sources.querysets import of_objects
from arealex.sources.shared import kept

METHODS = ("signature_scan", "token_overlap", "grid_overlap", "token_bounded", "grid_bounded", "two_filter", "pair", "quad_pair", "word_first", "area_first", "word_tree", "exact_scan")
LEVEL, BUDGET, QUAD_LEVEL = 6, 64, 5


def candidates(ix: P.Index, q: DataFrame, method: str, level: int = LEVEL, buckets: int | None = None, budget: int = BUDGET, max_level: int = QUAD_LEVEL, tested: bool = False, **options) -> DataFrame:
    """query_id, object_id: a superset of the answers for thresholds above 0. ``tested`` lets probes inside tasks leave out pairs whose areas aren't similar."""
    if method == "quad_pair":
        return Q.quad_pair(ix, q, kept(Q.pick_quad_cells(ix, budget, max_level, **options)), max_level, tested)
    if method == "pair":
        return P.pair(ix, q, level, buckets, tested)
    if method == "two_filter":
        return P.two_filter(ix, q, level, tested)
    if method == "word_tree":
        return B.word_tree_candidates(ix, q, **options)
    plain = {"signature_scan": P.signature_scan, "token_overlap": P.token_overlap, "token_bounded": P.token_bounded}
    if method in plain:
        return plain[method](ix, q, **options).select("query_id", "object_id")
    gridded = {"grid_overlap": P.grid_overlap, "grid_bounded": P.grid_bounded}
    return gridded[method](ix, q, level, **options).select("query_id", "object_id")


def _routed(ix: P.Index, q: DataFrame, method: str, **options) -> DataFrame:
    if method == "word_first":
        return B.word_first(ix, q)
    if method == "area_first":
        return B.area_first(ix, q, **options)
    if method == "exact_scan":
        return exact_scan(ix, q)
    return verify(ix, q, candidates(ix, q, method, tested=True, **options))


def shorter_lists(ix: P.Index, q: DataFrame, level: int) -> str:
    """The filter, by words or by the grid, whose lists for the batch's prefixes have fewer postings."""
    words = P.token_prefix(ix, q).agg(F.coalesce(F.sum("n_obj"), F.lit(0))).first()[0]
    cells = P.cell_prefix(ix, q, level).agg(F.coalesce(F.sum("n_obj"), F.lit(0))).first()[0]
    return "token_bounded" if words < cells else "grid_bounded"


def search(ix: P.Index, queries: DataFrame, method: str = "auto", **options) -> DataFrame:
    """query_id, object_id, inter_area, union_area, inter_w, union_w of all answers.

    A threshold of 0 lets through objects that share nothing, which no list holds: queries with one such threshold go to the filter of the other side, queries with two are held against all objects. ``auto`` takes the bounded probe whose lists are shorter in all.
    """
    q = P.known_size(queries)
    if method == "auto":
        method = shorter_lists(ix, q, options.get("level", LEVEL))
        options = {} if method == "token_bounded" else options
    routes = (
        ((F.col("tau_r_bp") > 0) & (F.col("tau_t_bp") > 0), method, options),
        ((F.col("tau_r_bp") <= 0) & (F.col("tau_t_bp") > 0), "token_bounded", {}),
        ((F.col("tau_r_bp") > 0) & (F.col("tau_t_bp") <= 0), "grid_bounded", {"level": options.get("level", LEVEL)}),
        ((F.col("tau_r_bp") <= 0) & (F.col("tau_t_bp") <= 0), "exact_scan", {}),
    )
    kinds = {(r[0] > 0, r[1] > 0) for r in q.select("tau_r_bp", "tau_t_bp").distinct().collect()}
    used = [(where, m, o) for (where, m, o), kind in zip(routes, ((True, True), (False, True), (True, False), (False, False)), strict=True) if kind in kinds]
    if not used:
        return exact_scan(ix, q)
    return reduce(DataFrame.unionByName, [_routed(ix, P.known_size(q.where(where)) if len(used) > 1 else q, m, **o) for where, m, o in used])


def top_k(answers: DataFrame, k: int) -> DataFrame:
    """Each query's k best answers by the product of both similarities."""
    from pyspark.sql import Window

    score = (F.col("inter_area") / F.col("union_area")) * (F.col("inter_w") / F.col("union_w"))
    w = Window.partitionBy("query_id").orderBy(F.desc(score), "object_id")
    return answers.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def self_search(ix: P.Index, tau_r_bp: int, tau_t_bp: int, level: int = LEVEL) -> DataFrame:
    """Every object against all: object_id, class_id and n_links, the class being its set of equal objects.

    Equal objects (sides and tokens) are one class, named by its smallest object; links are between objects of different classes, and counted inside tasks (``linking``): no pair is written. Thresholds of 0 and cosine take the links themselves.
    """
    one, owner = classes(ix)
    if K.fits(ix, tau_r_bp, tau_t_bp):
        counts = K.link_counts(one, tau_r_bp, tau_t_bp, level).withColumnRenamed("object_id", "class_id")
    else:
        counts = _links(one, tau_r_bp, tau_t_bp, level).select(F.explode(F.array("a", "b")).alias("class_id")).groupBy("class_id").agg(F.count("*").alias("n_links"))
    return owner.join(counts, "class_id", "left").select("object_id", "class_id", F.coalesce("n_links", F.lit(0).cast("bigint")).alias("n_links"))


def classes(ix: P.Index) -> tuple[P.Index, DataFrame]:
    """An index of the class representatives, with the weights and space of all objects, and (object_id, class_id)."""
    groups = ix.objects.select("object_id", *SIDES, F.sort_array(F.coalesce("tokens", F.array().cast("array<string>"))).alias("tokens"))
    found = kept(groups.groupBy(*SIDES, "tokens").agg(F.min("object_id").alias("class_id")))
    one = found.select(F.col("class_id").alias("object_id"), *SIDES, "tokens")
    return P.Index(one, ix.measure, ix.region_measure, ix.weighted, ix.order, ix.space, ix.stats), groups.join(found, [*SIDES, "tokens"]).select("object_id", "class_id")


def class_links(ix: P.Index, tau_r_bp: int, tau_t_bp: int, level: int = LEVEL) -> tuple[DataFrame, DataFrame]:
    """Links (a < b) between class representatives, with their measures, and (object_id, class_id)."""
    one, owner = classes(ix)
    return _links(one, tau_r_bp, tau_t_bp, level), owner


def _links(one: P.Index, tau_r_bp: int, tau_t_bp: int, level: int) -> DataFrame:
    o = one.full.select("object_id", area(box()).alias("area"), "w_total")
    tr, tt = F.lit(tau_r_bp).cast("bigint"), F.lit(tau_t_bp).cast("bigint")
    # What two objects share is at least tau times either total, so one prefix serves both sides.
    tokens = one.tokens.join(o, "object_id").where(P.shared_enough(F.col("bound_t"), F.col("w_total"), tt, one.measure)).select("object_id", "token")
    cells = one.cells(level).join(o, "object_id").where(P.shared_enough(F.col("bound_r"), F.col("area"), tr, one.region_measure)).select("object_id", "cell")
    posts = tokens.join(cells, "object_id").select("object_id", F.xxhash64("token", "cell").alias("element"))
    pairs = posts.join(posts.withColumnRenamed("object_id", "other"), "element").where("object_id < other").select("object_id", "other").distinct()
    q = of_objects(one.objects, tau_r_bp, tau_t_bp)
    found = verify(one, q, pairs.select(F.col("object_id").alias("query_id"), F.col("other").alias("object_id")))
    return found.withColumnsRenamed({"query_id": "a", "object_id": "b"})


def register_sql(spark) -> None:
    """SQL functions over rectangles given by four sides each: overlap_area and region_jaccard, as temporary SQL functions of the session."""
    args = ", ".join(f"{p}{s} BIGINT" for p in ("a_", "b_") for s in SIDES)
    shared = "GREATEST(LEAST(a_x1, b_x1) - GREATEST(a_x0, b_x0), 0) * GREATEST(LEAST(a_y1, b_y1) - GREATEST(a_y0, b_y0), 0)"
    total = "(a_x1 - a_x0) * (a_y1 - a_y0) + (b_x1 - b_x0) * (b_y1 - b_y0)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION overlap_area({args}) RETURNS BIGINT RETURN {shared}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION region_jaccard({args}) RETURNS DOUBLE RETURN CASE WHEN {total} - {shared} > 0 THEN CAST({shared} AS DOUBLE) / ({total} - {shared}) ELSE 0D END")
