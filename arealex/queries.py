"""Registered queries: each method, variant, baseline, measure and workload on the given tables, and its DuckDB twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arealex import oracle as O
from arealex.functions.cells import finest_level
from arealex.functions.similarity import SIDES
from arealex.operators import levels as L
from arealex.operators import probes as P
from arealex.operators import quadcells as Q
from arealex.operators import signatures as S
from arealex.operators.verify import verify
from arealex.plans import measures as M
from arealex.plans import search as X
from arealex.plans import workloads as W
from arealex.sources import objects as R
from arealex.sources.querysets import of_objects, query_set, with_thresholds
from arealex.sources.shared import kept, shared_path
from arealex.sources.store import build_index, load_index

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def _add(name: str, make: Query, sql: str | None = None) -> None:
    QUERIES[name] = make
    if sql:
        ORACLE_SQL[name] = sql


def _index(spark: SparkSession, sf_dir: str, kind: str, **options) -> P.Index:
    return P.Index(kept(R.SETS[kind](spark, sf_dir)), **options)


def _batch(spark: SparkSession, sf_dir: str, kind: str, queries: str, r: int, t: int, **options) -> tuple[P.Index, DataFrame]:
    ix = _index(spark, sf_dir, kind, **options)
    return ix, query_set(ix, queries, r, t)


def _with(kind: str, queries: str, r: int, t: int, body: Callable[[P.Index, DataFrame], DataFrame], **options) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return body(*_batch(spark, sf_dir, kind, queries, r, t, **options))

    return run


def _on(kind: str, body: Callable[[P.Index], DataFrame]) -> Query:
    return lambda spark, sf_dir: body(_index(spark, sf_dir, kind))


def _stored(spark: SparkSession, sf_dir: str):
    """An index of the users' days, written and opened again, with cells chosen for each token."""
    path = shared_path(spark, "index")
    build_index(_index(spark, sf_dir, "activity"), path, 6, shards=4, budget=64, max_level=5)
    return load_index(spark, path)


def _stored_answers(spark: SparkSession, sf_dir: str, method: str) -> DataFrame:
    ix = _stored(spark, sf_dir)
    return ix.search(query_set(ix, "large", 1000, 4000), method)


# Object sets and statistics.
for _kind in R.SETS:
    _add(
        f"objects_{_kind}",
        lambda spark, sf_dir, k=_kind: R.SETS[k](spark, sf_dir).select("object_id", *SIDES, F.array_join(F.sort_array("tokens"), " ").alias("tokens")),
        O.parts(_kind) + "\nSELECT object_id, x0, y0, x1, y1, coalesce(tokens, '') AS tokens FROM objects LEFT JOIN (SELECT object_id, string_agg(token, ' ' ORDER BY token) AS tokens FROM object_tokens GROUP BY object_id) USING (object_id)",
    )
    _add(f"token_stats_{_kind}", _on(_kind, lambda ix: ix.stats), O.parts(_kind) + "\nSELECT token, n_obj, w FROM stats")
    _add(
        f"dataset_stats_{_kind}",
        _on(_kind, M.dataset_stats),
        O.parts(_kind) + "\nSELECT (SELECT count(*) FROM objects) AS objects, (SELECT CAST(sum(area) AS BIGINT) FROM totals) AS area_sum, (SELECT count(*) FROM object_tokens) AS tokens_sum, (SELECT count(*) FROM stats) AS distinct_tokens, (SELECT CAST(1 AS BIGINT) << (xb + yb) FROM space) AS space_area",
    )
    _add(
        f"area_distribution_{_kind}",
        _on(_kind, M.area_distribution),
        O.parts(_kind) + "\nSELECT digits, objects, CAST(sum(objects) OVER (ORDER BY digits) AS BIGINT) AS upto FROM (SELECT length(CAST(area AS VARCHAR)) AS digits, count(*) AS objects FROM totals GROUP BY 1)",
    )
_add("query_set_activity_large", _with("activity", "large", 4000, 4000, lambda ix, q: q.select("query_id", *SIDES, F.array_join("tokens", " ").alias("tokens"))), O.parts("activity", "large") + "\nSELECT query_id, x0, y0, x1, y1, tokens FROM queries JOIN (SELECT query_id, string_agg(token, ' ' ORDER BY token) AS tokens FROM query_tokens GROUP BY query_id) USING (query_id)")
_add("query_set_shipment_small", _with("shipment", "small", 4000, 4000, lambda ix, q: q.select("query_id", *SIDES, F.array_join("tokens", " ").alias("tokens"))), O.parts("shipment", "small") + "\nSELECT query_id, x0, y0, x1, y1, tokens FROM queries JOIN (SELECT query_id, string_agg(token, ' ' ORDER BY token) AS tokens FROM query_tokens GROUP BY query_id) USING (query_id)")

# Answers: every method has the same ones.
for _kind, _q, _r, _t in (("activity", "large", 1000, 4000), ("activity", "small", 4000, 1000), ("shipment", "large", 4000, 4000), ("document", "large", 1000, 1000), ("document", "small", 2500, 3000)):
    _add(f"exact_scan_{_kind}_{_q}", _with(_kind, _q, _r, _t, lambda ix, q: X.search(ix, q, "exact_scan")), O.answers(_kind, _q, _r, _t))
for _m in X.METHODS[:-1]:
    _add(f"{_m}_answers_activity", _with("activity", "large", 2000, 2000, lambda ix, q, m=_m: X.search(ix, q, m)), O.answers("activity", "large", 2000, 2000))
for _m in ("two_filter", "pair", "word_first", "area_first"):
    _add(f"{_m}_answers_shipment", _with("shipment", "small", 4000, 1000, lambda ix, q, m=_m: X.search(ix, q, m)), O.answers("shipment", "small", 4000, 1000))
_add("pair_hashed_answers_activity", _with("activity", "small", 2500, 3000, lambda ix, q: X.search(ix, q, "pair", buckets=4096)), O.answers("activity", "small", 2500, 3000))
for _i in ("scan", "tree"):
    _add(f"area_first_{_i}_answers_activity", _with("activity", "large", 4000, 1000, lambda ix, q, i=_i: X.search(ix, q, "area_first", index=i)), O.answers("activity", "large", 4000, 1000))
for _name, _options in (("weighted_errors", {"mode": "children_weighted"}), ("finest_errors", {"mode": "finest"}), ("kept_empty", {"keep_empty": True}), ("total_budget", {"total": True})):
    _add(f"quad_pair_{_name}_answers_activity", _with("activity", "small", 4000, 4000, lambda ix, q, n=_name, o=_options: X.search(ix, q, "quad_pair", budget=4000 if n == "total_budget" else 32, max_level=4, **o)), O.answers("activity", "small", 4000, 4000))
for _o in ("frequent", "random", "code"):
    _add(f"order_{_o}_answers_activity", _with("activity", "large", 4000, 4000, lambda ix, q: X.search(ix, q, "two_filter"), order=_o), O.answers("activity", "large", 4000, 4000))
for _m in ("dice", "cosine"):
    _add(f"{_m}_answers_activity", _with("activity", "large", 1000, 4000, lambda ix, q: X.search(ix, q, "two_filter"), measure=_m), O.answers("activity", "large", 1000, 4000, _m))
_add("unweighted_answers_activity", _with("activity", "small", 1000, 4000, lambda ix, q: X.search(ix, with_thresholds(q, 1000, 4000), "two_filter"), weighted=False), O.answers("activity", "small", 1000, 4000, weighted=False))
_add("region_dice_answers_activity", _with("activity", "small", 4000, 4000, lambda ix, q: X.search(ix, q, "two_filter"), region_measure="dice"), O.answers("activity", "small", 4000, 4000).replace("WHERE 10000 * inter >= 4000 * (q.area + o.area - inter)", "WHERE 20000 * inter >= 4000 * (q.area + o.area)"))
_add("auto_search_document", _with("document", "large", 1000, 4000, X.search), O.answers("document", "large", 1000, 4000))
_add("only_words_document", _with("document", "small", 0, 4000, lambda ix, q: X.search(ix, q).select("query_id", "object_id", "inter_w", "union_w")), O.parts("document", "small") + "\nSELECT query_id, object_id, iw AS inter_w, q.w_total + o.w_total - iw AS union_w FROM (SELECT query_id, object_id, CAST(sum(qt.w) AS BIGINT) AS iw FROM query_tokens qt JOIN object_tokens ot USING (token) GROUP BY ALL) JOIN query_totals q USING (query_id) JOIN totals o USING (object_id) WHERE 10000 * iw >= 4000 * (q.w_total + o.w_total - iw) AND q.w_total + o.w_total > iw")
_add(
    "top_3_document",
    _with("document", "large", 1000, 1000, lambda ix, q: X.top_k(X.search(ix, q), 3).select("query_id", "object_id", "rank")),
    O.parts("document", "large") + O.answer_parts(1000, 1000) + "\nSELECT query_id, object_id, CAST(rank AS INTEGER) AS rank FROM (SELECT query_id, object_id, row_number() OVER (PARTITION BY query_id ORDER BY (inter_area / union_area) * (inter_w / union_w) DESC, object_id) AS rank FROM answers) WHERE rank <= 3",
)

# Candidates.
for _m in ("token_overlap", "grid_overlap", "token_bounded", "two_filter", "pair"):
    _add(f"{_m}_candidates", _with("activity", "large", 4000, 4000, lambda ix, q, m=_m: X.candidates(ix, q, m)), O.candidates("activity", "large", 4000, 4000, _m))
for _v in (4, 6, 8):
    _add(f"grid_bounded_candidates_l{_v}", _with("activity", "small", 4000, 1000, lambda ix, q, v=_v: X.candidates(ix, q, "grid_bounded", v)), O.candidates("activity", "small", 4000, 1000, "grid_bounded", _v))
_add("grid_bounded_recheck", _with("activity", "large", 4000, 4000, lambda ix, q: P.grid_bounded(ix, q, 6, recheck_sum=True)), O.candidates("activity", "large", 4000, 4000, "grid_overlap"))
_add("token_bounded_recheck", _with("activity", "large", 4000, 4000, lambda ix, q: P.token_bounded(ix, q, recheck_sum=True)), O.candidates("activity", "large", 4000, 4000, "token_overlap"))
for _name, _o in (("prefix_only", {"use_bound": False}), ("bound_only", {"use_prefix": False})):
    _sql = O.parts("activity", "large", (6,)) + O.grid_hits(4000, 6)
    _sql = _sql.replace("WHERE 10000 * bound_r >= 4000 * area", "") if _name == "prefix_only" else _sql.replace("WHERE 10000 * rest >= 4000 * area", "")
    _add(f"grid_{_name}_candidates", _with("activity", "large", 4000, 4000, lambda ix, q, o=_o: P.grid_bounded(ix, q, 6, **o)), _sql + "\nSELECT DISTINCT query_id, object_id FROM gh6")
_add("pair_hashed_candidates", _with("activity", "small", 4000, 4000, lambda ix, q: X.candidates(ix, q, "pair", 6, 1024)), O.hashed_pairs("activity", "small", 4000, 4000, 6, 1024))
_add("quad_pair_candidates", _with("activity", "small", 4000, 4000, lambda ix, q: X.candidates(ix, q, "quad_pair")))
_add(
    "size_filter_candidates",
    _with("activity", "large", 4000, 4000, lambda ix, q: P.size_filter(ix, q, P.two_filter(ix, q, 6))),
    O.candidates("activity", "large", 4000, 4000, "two_filter").replace("\nSELECT query_id, object_id FROM th", ",\nboth_ AS (SELECT query_id, object_id FROM th") + ")\nSELECT query_id, object_id FROM both_ JOIN query_totals q USING (query_id) JOIN totals o USING (object_id) WHERE 10000 * o.area >= 4000 * q.area AND 10000 * q.area >= 4000 * o.area AND 10000 * o.w_total >= 4000 * q.w_total AND 10000 * q.w_total >= 4000 * o.w_total",
)

# Signatures.
_add("grid_signature_shipment_l6", _on("shipment", lambda ix: S.grid_signature(ix.objects, ix.space, 6)), O.parts("shipment", levels=(6,)) + "\nSELECT object_id, cell, w FROM oc6")
_add("token_postings_document", _on("document", lambda ix: ix.tokens), O.parts("document") + "\nSELECT object_id, token, w, CAST(sum(w) OVER (PARTITION BY object_id ORDER BY n_obj, token ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS bound_t FROM signed")
_add("cell_postings_document_l6", _on("document", lambda ix: ix.cells(6)), O.parts("document", levels=(6,)) + "\nSELECT object_id, cell, w, n_obj, CAST(sum(w) OVER (PARTITION BY object_id ORDER BY n_obj, cell ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS bound_r FROM oc6 JOIN cs6 USING (cell)")

# Measures.
_add("overlap_count_activity", _with("activity", "large", 4000, 4000, lambda ix, q: M.overlap_count(ix, q)), O.parts("activity", "large") + "\nSELECT query_id, count(*) AS n_overlap FROM queries q JOIN objects o ON q.x0 < o.x1 AND o.x0 < q.x1 AND q.y0 < o.y1 AND o.y0 < q.y1 GROUP BY query_id")
_add("query_cost_grid", _with("activity", "large", 4000, 4000, lambda ix, q: M.probe_cost(P.grid_bounded_hits(ix, q, 6), P.cell_prefix(ix, q, 6))), O.parts("activity", "large", (6,)) + O.grid_hits(4000, 6) + "\nSELECT query_id, lists, coalesce(retrieved, 0) AS retrieved, coalesce(candidates, 0) AS candidates, round(1.0::DOUBLE * coalesce(retrieved, 0) + 10.0 * coalesce(candidates, 0), 6) AS cost FROM (SELECT query_id, count(*) AS lists FROM qcp6 GROUP BY 1) LEFT JOIN (SELECT query_id, count(*) AS retrieved, count(DISTINCT object_id) AS candidates FROM gh6 GROUP BY 1) USING (query_id)")
_add("filter_quality_two_filter", _with("activity", "small", 2000, 2000, lambda ix, q: M.filter_quality(ix, q, P.two_filter(ix, q, 6))), O.parts("activity", "small", (6,)) + O.token_hits(2000) + O.grid_hits(2000, 6) + O.answer_parts(2000, 2000) + "\nSELECT (SELECT count(*) FROM (SELECT query_id, object_id FROM th INTERSECT SELECT query_id, object_id FROM gh6)) AS candidates, (SELECT count(*) FROM answers) AS answers, 0::BIGINT AS missed")
_add("filter_quality_quad", _with("activity", "small", 2000, 2000, lambda ix, q: M.filter_quality(ix, q, X.candidates(ix, q, "quad_pair", budget=32, max_level=4)).select("answers", "missed")), O.parts("activity", "small") + O.answer_parts(2000, 2000) + "\nSELECT count(*) AS answers, 0::BIGINT AS missed FROM answers")
_add("bound_tightness_l6", _with("activity", "large", 4000, 4000, lambda ix, q: M.bound_tightness(ix, q, 6)), O.parts("activity", "large", (6,)) + "\nSELECT query_id, CAST(sum(b) AS BIGINT) AS bound_sum, CAST(sum(greatest(0, least(q.x1, o.x1) - greatest(q.x0, o.x0)) * greatest(0, least(q.y1, o.y1) - greatest(q.y0, o.y0))) AS BIGINT) AS true_sum FROM (SELECT query_id, object_id, sum(least(a.w, c.w)) AS b FROM qc6 a JOIN oc6 c USING (cell) GROUP BY ALL) JOIN queries q USING (query_id) JOIN objects o USING (object_id) GROUP BY query_id")
_add("index_size_activity", _on("activity", lambda ix: M.index_size(ix, [4, 6], buckets=4096, budget=0)), O.parts("activity", levels=(4, 6)) + "\nSELECT 'token' AS kind, (SELECT count(*) FROM stats) AS elements, (SELECT count(*) FROM object_tokens) AS postings" + "".join(f" UNION ALL SELECT 'grid{v}', count(DISTINCT cell), count(*) FROM oc{v} UNION ALL SELECT 'pair{v}', count(DISTINCT (token, cell)), count(*) FROM oc{v} JOIN object_tokens USING (object_id) UNION ALL SELECT 'hashed{v}', count(DISTINCT b), count(*) FROM (SELECT DISTINCT object_id, CAST('0x' || substr(md5(token || ':' || cell), 1, 8) AS BIGINT) % 4096 AS b FROM oc{v} JOIN object_tokens USING (object_id))" for v in (4, 6)))
_add("index_size_quad_activity", _on("activity", lambda ix: M.index_size(ix, [], buckets=None, budget=64)))
_add("index_bytes_activity", lambda spark, sf_dir: _stored(spark, sf_dir).sizes())
for _m in ("two_filter", "grid_bounded", "quad_pair"):
    _add(f"stored_{_m}_answers_activity", lambda spark, sf_dir, m=_m: _stored_answers(spark, sf_dir, m), O.answers("activity", "large", 1000, 4000))
_add("nodes_visited_activity", _with("activity", "large", 4000, 4000, lambda ix, q: M.nodes_visited(ix, q)), O.tree_visits("activity", "large", 4000, 4000))
_add("exact_cell_weight_candidates", _with("activity", "large", 4000, 4000, lambda ix, q: P.grid_overlap(ix, q, 6, "exact")), O.parts("activity", "large") + "\nSELECT query_id, object_id, inter AS shared FROM (SELECT q.query_id, o.object_id, (least(q.x1, o.x1) - greatest(q.x0, o.x0)) * (least(q.y1, o.y1) - greatest(q.y0, o.y0)) AS inter FROM queries q JOIN objects o ON q.x0 < o.x1 AND o.x0 < q.x1 AND q.y0 < o.y1 AND o.y0 < q.y1) JOIN query_totals USING (query_id) WHERE 10000 * inter >= 4000 * area")
_add("finest_level_activity", _on("activity", lambda ix: ix.objects.sparkSession.range(1).select(F.lit(finest_level(ix.space)).alias("level"))), O.parts("activity") + "\nSELECT CAST(greatest(xb, yb) AS INTEGER) AS level FROM space")
_add("region_ratios_document", _with("document", "large", 1000, 1000, lambda ix, q: verify(ix, q).select("query_id", "object_id", F.round(F.col("inter_area") / F.col("union_area"), 6).alias("sim_r"), F.round(F.col("inter_w") / F.col("union_w"), 6).alias("sim_t"))), O.parts("document", "large") + O.answer_parts(1000, 1000) + "\nSELECT query_id, object_id, round(inter_area / union_area, 6) AS sim_r, round(inter_w / union_w, 6) AS sim_t FROM answers")

# Levels.
_LEVELS = [2, 3, 4, 5, 6]
_COSTS = O.parts("activity", "large", tuple(_LEVELS)) + "".join(O.grid_hits(4000, v) for v in _LEVELS) + ",\ncosts AS (" + " UNION ALL ".join(f"SELECT {v} AS level, (SELECT CAST(coalesce(sum(n_obj), 0) AS BIGINT) FROM qc{v} JOIN cs{v} USING (cell)) AS retrieved, (SELECT count(*) FROM (SELECT DISTINCT query_id, object_id FROM gh{v})) AS candidates" for v in _LEVELS) + "),\npriced AS (SELECT *, round((1.0::DOUBLE * retrieved + 10.0 * candidates) / (SELECT count(*) FROM queries), 6) AS cost FROM costs)"
_add("level_cost", _with("activity", "large", 4000, 4000, lambda ix, q: L.expected_level_cost(ix, q, _LEVELS)), _COSTS + "\nSELECT * FROM priced")
_add("level_benefit", _with("activity", "large", 4000, 4000, lambda ix, q: L.level_benefits(L.expected_level_cost(ix, q, _LEVELS))), _COSTS + "\nSELECT level, cost, round(cost - lead(cost) OVER (ORDER BY level), 6) AS benefit FROM priced")
_add("pick_level", _with("activity", "large", 4000, 4000, lambda ix, q: L.pick_level(L.expected_level_cost(ix, q, _LEVELS), 100.0)), _COSTS + "\nSELECT coalesce(min(CASE WHEN benefit < 100 THEN level END), max(level)) AS level FROM (SELECT level, round(cost - lead(cost) OVER (ORDER BY level), 6) AS benefit FROM priced)")
_add("best_level", _with("activity", "large", 4000, 4000, lambda ix, q: L.best_level(L.expected_level_cost(ix, q, _LEVELS))), _COSTS + "\nSELECT level, cost FROM priced ORDER BY cost, level LIMIT 1")
_add("cell_filter_benefit_l4", _with("activity", "large", 4000, 4000, lambda ix, q: L.cell_filter_benefit(ix, q, 4)), O.parts("activity", "large", (4, 5)) + ",\nu4 AS (SELECT cell, count(*) * any_value(n_obj) AS v FROM qc4 JOIN cs4 USING (cell) GROUP BY cell),\nu5 AS (SELECT cell >> 2 AS cell, sum(v) AS v FROM (SELECT cell, count(*) * any_value(n_obj) AS v FROM qc5 JOIN cs5 USING (cell) GROUP BY cell) GROUP BY 1)\nSELECT u4.cell, round(CAST(u4.v - coalesce(u5.v, 0) AS DOUBLE) / (SELECT count(*) FROM queries), 6) AS benefit FROM u4 LEFT JOIN u5 USING (cell)")

# Cells for each token.
_TREE = O.parts("activity", levels=(0, 1, 2, 3)) + ",\ntc AS (" + " UNION ALL ".join(f"SELECT token, {v} AS level, cell, count(*) AS n_obj, sum(w) / ((SELECT CAST(1 AS BIGINT) << (greatest(0, xb - {v}) + greatest(0, yb - {v})) FROM space)::DOUBLE) AS x FROM oc{v} JOIN object_tokens USING (object_id) GROUP BY ALL" for v in range(4)) + "),\nch AS (SELECT token, level - 1 AS level, cell >> 2 AS cell, sum(x) AS s1, sum(x * x) AS s2 FROM tc WHERE level > 0 GROUP BY ALL)"
_add("expected_list_size", _on("activity", lambda ix: Q.expected_sizes(ix, Q.token_cells(ix, 3), 3).select("token", "level", "cell", "n_obj", F.round("x", 6).alias("x"))), _TREE + "\nSELECT token, level, cell, n_obj, round(x, 6) AS x FROM tc")
_ERR = "greatest(coalesce(s2, 0) - 2 * x * coalesce(s1, 0) + 4 * x * x, 0)"
for _mode, _sql in (("children", f"CASE WHEN level = 3 THEN 0 ELSE {_ERR} END"), ("children_weighted", f"CASE WHEN level = 3 THEN 0 ELSE pow(4.0, 2 - level) * {_ERR} END")):
    _add(f"cell_error_{_mode}", _on("activity", lambda ix, m=_mode: Q.cell_error(ix, Q.token_cells(ix, 3), 3, m).select("token", "level", "cell", F.round("error", 3).alias("error"))), _TREE + f"\nSELECT token, level, cell, round({_sql}, 3) AS error FROM tc LEFT JOIN ch USING (token, level, cell)")
_add("cell_error_finest", _on("activity", lambda ix: Q.cell_error(ix, Q.token_cells(ix, 3), 3, "finest").select("token", "level", "cell", F.round("error", 3).alias("error"))), _TREE + ",\nfi AS (SELECT token, v AS level, cell >> (2 * (3 - v)) AS cell, sum(x) AS s1, sum(x * x) AS s2 FROM tc, (SELECT unnest([0, 1, 2, 3]) AS v) WHERE level = 3 GROUP BY ALL)\nSELECT token, level, cell, round(greatest(coalesce(s2, 0) - 2 * x * coalesce(s1, 0) + pow(4.0, 3 - level) * x * x, 0), 3) AS error FROM tc LEFT JOIN fi USING (token, level, cell)")
_add("quad_selection", _on("activity", lambda ix: Q.pick_quad_cells(ix, 16, 4)))

# Workloads.
for _kind, _q in (("activity", "large"), ("activity", "small"), ("shipment", "large"), ("shipment", "small")):
    _add(f"workload_token_or_grid_{_kind}_{_q}", _on(_kind, lambda ix, q=_q: W.token_or_grid(ix, q, [6, 8])), O.token_or_grid(_kind, _q, [6, 8], W.SETTINGS))
    _add(f"workload_comparison_{_kind}_{_q}", _on(_kind, lambda ix, q=_q: W.comparison(ix, q)), O.comparison(_kind, _q, W.SETTINGS, W.COMPARED))
for _q in ("large", "small"):
    _add(f"workload_granularity_{_q}", _on("activity", lambda ix, q=_q: W.granularity(ix, q, list(range(4, 11)))), O.parts("activity", _q, tuple(range(4, 11))) + "".join(O.grid_hits(4000, v) for v in range(4, 11)) + "\n" + " UNION ALL ".join(O.hits_row(f"{v} AS level", f"gh{v}") for v in range(4, 11)))
    _add(f"workload_grid_or_pair_{_q}", _on("activity", lambda ix, q=_q: W.grid_or_pair(ix, q, [8, 9, 10])), O.grid_or_pair("activity", _q, [8, 9, 10], W.SETTINGS))
    _add(f"workload_pair_or_quad_{_q}", _on("activity", lambda ix, q=_q: W.pair_or_quad(ix, q, [4, 5], [16, 64], 5)))
_PAIRS = [(1000, 1000), (1000, 4000), (4000, 1000), (4000, 4000)]
_add(
    "threshold_cube",
    _on("activity", lambda ix: W.sweep_answers(ix, "large", _PAIRS)),
    O.parts("activity", "large") + "".join(O.answer_parts(r, t).replace("near AS", f"near{k} AS").replace("FROM near n", f"FROM near{k} n").replace("alike", f"alike{k}").replace("shared", f"shared{k}").replace("answers AS", f"answers{k} AS") for k, (r, t) in enumerate(_PAIRS)) + ",\nall_ AS (" + " UNION ALL ".join(f"SELECT {r} AS tau_r_bp, {t} AS tau_t_bp, query_id FROM answers{k}" for k, (r, t) in enumerate(_PAIRS)) + ")\nSELECT coalesce(tau_r_bp, -1) AS tau_r_bp, coalesce(tau_t_bp, -1) AS tau_t_bp, answers, queries FROM (SELECT tau_r_bp, tau_t_bp, count(*) AS answers, count(DISTINCT query_id) AS queries FROM all_ GROUP BY CUBE (tau_r_bp, tau_t_bp))",
)
_add("workload_scaling_pair", lambda spark, sf_dir: W.scaling(kept(R.shipment(spark, sf_dir)), [20, 40, 60, 80, 100]), O.scaling("shipment", "large", [20, 40, 60, 80, 100], 4000, 4000, X.LEVEL))
_add("workload_scaling_quad", lambda spark, sf_dir: W.scaling(kept(R.shipment(spark, sf_dir)), [20, 40, 60, 80, 100], method="quad_pair"))
_add("self_search_document", _on("document", lambda ix: X.self_search(ix, 1000, 4000)), O.parts("document") + """,
cls AS (SELECT object_id, min(object_id) OVER (PARTITION BY x0, y0, x1, y1, tk) AS class_id FROM objects LEFT JOIN (SELECT object_id, string_agg(token, ' ' ORDER BY token) AS tk FROM object_tokens GROUP BY 1) USING (object_id)),
rep AS (SELECT o.*, t.area, t.w_total FROM objects o JOIN totals t USING (object_id) WHERE object_id IN (SELECT class_id FROM cls)),
nr AS (SELECT a.object_id AS a, b.object_id AS b, a.w_total + b.w_total AS ws FROM rep a JOIN rep b ON a.object_id < b.object_id AND a.x0 < b.x1 AND b.x0 < a.x1 AND a.y0 < b.y1 AND b.y0 < a.y1
       WHERE 10000 * (least(a.x1, b.x1) - greatest(a.x0, b.x0)) * (least(a.y1, b.y1) - greatest(a.y0, b.y0)) >= 1000 * (a.area + b.area - (least(a.x1, b.x1) - greatest(a.x0, b.x0)) * (least(a.y1, b.y1) - greatest(a.y0, b.y0)))),
lk AS (SELECT a, b FROM (SELECT a, b, ws, sum(s.w) AS iw FROM nr JOIN signed s ON s.object_id = a JOIN object_tokens t ON t.object_id = b AND t.token = s.token GROUP BY ALL) WHERE 10000 * iw >= 4000 * (ws - iw)),
n AS (SELECT id, count(*) AS n FROM (SELECT a AS id FROM lk UNION ALL SELECT b FROM lk) GROUP BY id)
SELECT object_id, class_id, coalesce(n.n, 0) AS n_links FROM cls LEFT JOIN n ON id = class_id""")


def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seven objects and one query, as in ``objects.worked_example`` (which the tests hold to figures worked out by hand), on a table: the first seven users' events, and the first of them as the query."""
    ix = P.Index(kept(R.first_users(spark, sf_dir)))
    return X.search(ix, of_objects(ix.objects.where("object_id = 0"), 2500, 3000))


_add("worked_example", worked_example, O.first_users(7) + O.answer_parts(2500, 3000) + "\nSELECT * FROM answers")


def stream_window_objects(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All day windows that a run over the events so far closes, read back from the table that the stream wrote."""
    from arealex.streaming.windows import event_stream, windowed_objects

    base = shared_path(spark, "stream")
    events = event_stream(spark, sf_dir, spark.read.parquet(f"{sf_dir}/events.parquet").schema)
    run = windowed_objects(events).writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.parquet(f"{base}/out").select("user_id", "start", *SIDES, F.array_join(F.sort_array("tokens"), " ").alias("tokens"))


_add(
    "stream_window_objects",
    stream_window_objects,
    r"""WITH e AS (SELECT user_id, epoch_us(ts) // 86400000000 * 86400 AS start, epoch_us(ts) // 60000000 AS m, CAST(round(value * 100) AS BIGINT) AS v, event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events),
t AS (SELECT user_id, start, event_type AS token FROM e UNION SELECT user_id, start, 'k' || (k // 5) FROM e)
SELECT user_id, start, x0, y0, x1, y1, tokens FROM (SELECT user_id, start, min(m) AS x0, min(v) AS y0, max(m) + 1 AS x1, max(v) + 1 AS y1 FROM e GROUP BY ALL) JOIN (SELECT user_id, start, string_agg(token, ' ' ORDER BY token) AS tokens FROM t GROUP BY ALL) USING (user_id, start)
WHERE start + 86400 <= (SELECT max(epoch_us(ts)) // 1000000 FROM events) - 7200""",
)