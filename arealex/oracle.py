"""DuckDB SQL for the registered queries, put together from common parts."""

from __future__ import annotations

_OBJECTS = {
    "activity": r"""
rows_ AS (SELECT user_id * 100 + m // 1440 AS object_id, m AS x0, v AS y0, m + 1 AS x1, v + 1 AS y1, event_type, k FROM (
  SELECT user_id, event_type, (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01 00:00:00')) // 60000000 AS m, CAST(round(value * 100) AS BIGINT) AS v,
         CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events)),
objects AS (SELECT object_id, min(x0) AS x0, min(y0) AS y0, max(x1) AS x1, max(y1) AS y1 FROM rows_ GROUP BY object_id),
object_tokens AS (SELECT object_id, event_type AS token FROM rows_ UNION SELECT object_id, 'k' || (k // 5) FROM rows_ UNION SELECT object_id, event_type || ':' || (k // 20) FROM rows_)""",
    "shipment": r"""
rows_ AS (SELECT l_orderkey * 1000000 + l_partkey AS object_id, date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS d, CAST(l_quantity AS BIGINT) AS q,
  CAST(round(l_extendedprice) AS BIGINT) AS p, 200 + 100 * CAST(round(100 * (l_discount + l_tax)) AS BIGINT) AS h, p_name, p_brand, p_type, p_size, c_mktsegment, o_orderpriority, o_orderstatus, c_nationkey, l_returnflag, l_linestatus
  FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey),
objects AS (SELECT object_id, min(d - q) AS x0, min(p - h) AS y0, max(d + q) AS x1, max(p + h) AS y1 FROM rows_ GROUP BY object_id),
object_tokens AS (SELECT DISTINCT object_id, unnest(list_concat(string_split(p_name, ' '), [p_brand, p_type, 'size' || (p_size // 10), c_mktsegment, o_orderpriority, 'st' || o_orderstatus, 'nation' || c_nationkey, 'rf' || l_returnflag, 'ls' || l_linestatus])) AS token FROM rows_)""",
    "document": r"""
rows_ AS (SELECT doc_id AS object_id, CAST(regexp_extract(source, '(\d+)', 1) AS BIGINT) AS s, (doc_id * 7919 + 104729) % 1000003 AS h1, (doc_id * 15485863 + 32452843) % 1000003 AS h2, text FROM documents),
objects AS (SELECT object_id, x0, y0, x0 + 1500 + (31 * h1 + h2) % 9500 AS x1, y0 + 1500 + (31 * h2 + h1) % 9500 AS y1 FROM (SELECT *, (s % 5) * 20000 + h1 % 6000 AS x0, (s // 5) * 20000 + h2 % 6000 AS y0 FROM rows_)),
words_ AS (SELECT object_id, token, count(*) AS c FROM (SELECT object_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS token FROM rows_) WHERE token <> '' GROUP BY ALL),
object_tokens AS (SELECT object_id, token FROM (SELECT *, row_number() OVER (PARTITION BY object_id ORDER BY c DESC, token) AS r FROM words_) WHERE r <= 14)""",
}

_STATS = """
stats AS (SELECT token, count(*) AS n_obj, CAST(round(ln((SELECT count(*) FROM objects) / count(*)) * 1000000) AS BIGINT) AS w FROM object_tokens GROUP BY token),
signed AS (SELECT object_id, token, w, n_obj FROM object_tokens JOIN stats USING (token)),
totals AS (SELECT o.object_id, (x1 - x0) * (y1 - y0) AS area, coalesce(t.w, 0) AS w_total FROM objects o LEFT JOIN (SELECT object_id, CAST(sum(w) AS BIGINT) AS w FROM signed GROUP BY object_id) t USING (object_id)),
space AS (SELECT min(x0) AS sx, min(y0) AS sy, length(ltrim(bin(max(x1) - min(x0) - 1), '0')) AS xb, length(ltrim(bin(max(y1) - min(y0) - 1), '0')) AS yb FROM objects)"""

#: The same, with each token's weight 1 (in millionths).
_PLAIN_STATS = _STATS.replace("CAST(round(ln((SELECT count(*) FROM objects) / count(*)) * 1000000) AS BIGINT)", "1000000::BIGINT")


def _queries(kind: str) -> str:
    large = kind == "large"
    sign = "-" if large else "+"
    back = "+" if large else "-"
    tokens = (
        "query_tokens AS (SELECT query_id, token, w, n_obj FROM (SELECT c.object_id AS query_id, token, w, n_obj, row_number() OVER (PARTITION BY c.object_id ORDER BY w DESC, token) AS r FROM chosen c JOIN signed USING (object_id)) WHERE r <= 7)"
        if large
        else "query_tokens AS (SELECT c.object_id AS query_id, token, w, n_obj FROM chosen c JOIN signed USING (object_id))"
    )
    return f"""
seeds AS (SELECT *, row_number() OVER (ORDER BY area {"DESC" if large else "ASC"}, object_id) - 1 AS rk, count(*) OVER () AS n FROM (SELECT *, (x1 - x0) * (y1 - y0) AS area FROM objects) WHERE area >= 64),
chosen AS (SELECT * FROM seeds WHERE rk < n // 4 AND rk % greatest(1, n // 400) = 0 ORDER BY rk LIMIT 100),
queries AS (SELECT object_id AS query_id, x0 {sign} (x1 - x0) // 16 AS x0, y0 {sign} (y1 - y0) // 16 AS y0, x1 {back} (x1 - x0) // 16 AS x1, y1 {back} (y1 - y0) // 16 AS y1 FROM chosen),
{tokens},
query_totals AS (SELECT query_id, (x1 - x0) * (y1 - y0) AS area, coalesce(t.w, 0) AS w_total FROM queries LEFT JOIN (SELECT query_id, CAST(sum(w) AS BIGINT) AS w FROM query_tokens GROUP BY query_id) t USING (query_id))"""


def cells(name: str, source: str, key: str, level: int) -> str:
    """CTEs that give ``name`` (key, cell, w) for the rectangles of ``source``."""
    spread = ""
    inner = f"{name}_c"
    for k, (shift, mask) in enumerate(((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555))):
        spread += f"{name}_s{k} AS (SELECT * REPLACE (((zx << {shift}) | zx) & {mask} AS zx, ((zy << {shift}) | zy) & {mask} AS zy) FROM {inner}),\n"
        inner = f"{name}_s{k}"
    return f"""
{name}_r AS (SELECT s.{key}, s.x0, s.y0, s.x1, s.y1, sx, sy, greatest(0, xb - {level}) AS kx, greatest(0, yb - {level}) AS ky, xb, yb FROM {source} s, space),
{name}_x AS (SELECT *, unnest(generate_series(greatest(0, (x0 - sx) >> kx), least((1 << (xb - kx)) - 1, (greatest(x1 - 1, x0) - sx) >> kx))) AS cx FROM {name}_r WHERE x1 > sx AND y1 > sy AND x0 < sx + (1 << xb) AND y0 < sy + (1 << yb)),
{name}_c AS (SELECT *, cx AS zx, cy AS zy FROM (SELECT *, unnest(generate_series(greatest(0, (y0 - sy) >> ky), least((1 << (yb - ky)) - 1, (greatest(y1 - 1, y0) - sy) >> ky))) AS cy FROM {name}_x)),
{spread}{name} AS (SELECT {key}, zx | (zy << 1) AS cell, w FROM (SELECT *, greatest(0, least(x1, sx + ((cx + 1) << kx)) - greatest(x0, sx + (cx << kx))) * greatest(0, least(y1, sy + ((cy + 1) << ky)) - greatest(y0, sy + (cy << ky))) AS w FROM {inner}) WHERE w > 0)""".replace("(x0 - sx) >> kx", "(CASE WHEN x0 < sx THEN 0 ELSE (x0 - sx) >> kx END)").replace("(y0 - sy) >> ky", "(CASE WHEN y0 < sy THEN 0 ELSE (y0 - sy) >> ky END)")


def parts(kind: str, queries: str | None = None, levels: tuple[int, ...] = (), weighted: bool = True) -> str:
    """WITH ... up to the parts that are asked for."""
    out = [_OBJECTS[kind], _STATS if weighted else _PLAIN_STATS]
    if queries:
        out.append(_queries(queries))
    for v in levels:
        out.append(cells(f"oc{v}", "objects", "object_id", v))
        out.append(f"\ncs{v} AS (SELECT cell, count(*) AS n_obj FROM oc{v} GROUP BY cell)")
        if queries:
            out.append(cells(f"qc{v}", "queries", "query_id", v))
    return "WITH " + ",".join(out)


def first_users(n: int) -> str:
    """The first users as objects, and the first of them as the query."""
    objects = _OBJECTS["activity"].replace("user_id * 100 + m // 1440 AS object_id", "user_id AS object_id").replace("FROM events)", f"FROM events WHERE user_id < {n})")
    return "WITH " + objects + "," + _STATS + """,
queries AS (SELECT object_id AS query_id, x0, y0, x1, y1 FROM objects WHERE object_id = 0),
query_tokens AS (SELECT object_id AS query_id, token, w, n_obj FROM signed WHERE object_id = 0),
query_totals AS (SELECT object_id AS query_id, area, w_total FROM totals WHERE object_id = 0)"""


_SUFFIX = "ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING"

TOKEN_TEST = {
    "jaccard": "10000 * iw >= {t} * (q.w_total + o.w_total - iw) AND q.w_total + o.w_total - iw > 0",
    "dice": "20000 * iw >= {t} * (q.w_total + o.w_total) AND q.w_total + o.w_total > 0",
    "cosine": "10000::HUGEINT * 10000 * iw * iw >= {t}::HUGEINT * {t} * q.w_total * o.w_total AND q.w_total > 0 AND o.w_total > 0",
}


def answer_parts(r: int, t: int, measure: str = "jaccard") -> str:
    return f""",
near AS (SELECT q.query_id, o.object_id, (least(q.x1, o.x1) - greatest(q.x0, o.x0)) * (least(q.y1, o.y1) - greatest(q.y0, o.y0)) AS inter FROM queries q JOIN objects o ON q.x0 < o.x1 AND o.x0 < q.x1 AND q.y0 < o.y1 AND o.y0 < q.y1),
alike AS (SELECT n.query_id, n.object_id, inter, q.area + o.area - inter AS union_area FROM near n JOIN query_totals q USING (query_id) JOIN totals o USING (object_id) WHERE 10000 * inter >= {r} * (q.area + o.area - inter)),
shared AS (SELECT a.query_id, a.object_id, CAST(sum(qt.w) AS BIGINT) AS iw FROM alike a JOIN object_tokens ot USING (object_id) JOIN query_tokens qt ON qt.query_id = a.query_id AND qt.token = ot.token GROUP BY ALL),
answers AS (SELECT query_id, object_id, inter AS inter_area, union_area, iw AS inter_w, q.w_total + o.w_total - iw AS union_w FROM alike JOIN shared USING (query_id, object_id) JOIN query_totals q USING (query_id) JOIN totals o USING (object_id) WHERE {TOKEN_TEST[measure].format(t=t)})"""


def answers(kind: str, queries: str, r: int, t: int, measure: str = "jaccard", weighted: bool = True) -> str:
    return parts(kind, queries, weighted=weighted) + answer_parts(r, t, measure) + "\nSELECT * FROM answers"


def token_hits(t: int) -> str:
    return f""",
tp AS (SELECT object_id, token, sum(w) OVER (PARTITION BY object_id ORDER BY n_obj, token {_SUFFIX}) AS bound_t FROM signed),
qp AS (SELECT query_id, token, w_total FROM (SELECT *, sum(w) OVER (PARTITION BY query_id ORDER BY n_obj, token {_SUFFIX}) AS rest FROM query_tokens) JOIN query_totals USING (query_id) WHERE 10000 * rest >= {t} * w_total),
th AS (SELECT query_id, object_id, token FROM qp JOIN tp USING (token) WHERE 10000 * bound_t >= {t} * w_total)"""


def grid_hits(r: int, v: int) -> str:
    return f""",
cp{v} AS (SELECT object_id, cell, sum(w) OVER (PARTITION BY object_id ORDER BY n_obj, cell {_SUFFIX}) AS bound_r FROM oc{v} JOIN cs{v} USING (cell)),
qcp{v} AS (SELECT query_id, cell, area FROM (SELECT *, sum(w) OVER (PARTITION BY query_id ORDER BY n_obj, cell {_SUFFIX}) AS rest FROM qc{v} JOIN cs{v} USING (cell)) JOIN query_totals USING (query_id) WHERE 10000 * rest >= {r} * area),
gh{v} AS (SELECT query_id, object_id, cell FROM qcp{v} JOIN cp{v} USING (cell) WHERE 10000 * bound_r >= {r} * area)"""


def candidates(kind: str, queries: str, r: int, t: int, method: str, v: int = 6) -> str:
    head = parts(kind, queries, (v,) if method not in ("token_overlap", "token_bounded") else ())
    if method == "token_overlap":
        return head + f"\nSELECT query_id, object_id FROM (SELECT query_id, object_id, sum(qt.w) AS iw FROM query_tokens qt JOIN object_tokens ot USING (token) GROUP BY ALL) JOIN query_totals USING (query_id) WHERE 10000 * iw >= {t} * w_total"
    if method == "grid_overlap":
        return head + f"\nSELECT query_id, object_id FROM (SELECT query_id, object_id, sum(least(a.w, b.w)) AS s FROM qc{v} a JOIN oc{v} b USING (cell) GROUP BY ALL) JOIN query_totals USING (query_id) WHERE 10000 * s >= {r} * area"
    if method == "token_bounded":
        return head + token_hits(t) + "\nSELECT DISTINCT query_id, object_id FROM th"
    if method == "grid_bounded":
        return head + grid_hits(r, v) + f"\nSELECT DISTINCT query_id, object_id FROM gh{v}"
    if method in ("two_filter", "pair"):
        return head + token_hits(t) + grid_hits(r, v) + f"\nSELECT query_id, object_id FROM th INTERSECT SELECT query_id, object_id FROM gh{v}"
    raise ValueError(method)


def hits_row(labels: str, hits: str) -> str:
    return f"SELECT {labels}, count(*) AS retrieved, count(DISTINCT (query_id, object_id)) AS candidates FROM {hits}"


def _settings(settings) -> str:
    rows = ", ".join(f"({r}, {t})" for r, t in settings)
    return f""",
settings AS (SELECT * FROM (VALUES {rows}) AS v(r, t))"""


def swept_grid(v: int) -> str:
    """The postings that the grid filter of a level retrieves under each setting's area threshold: gs (r, query_id, object_id)."""
    return f""",
gr{v} AS (SELECT query_id, cell, area, rest FROM (SELECT *, sum(w) OVER (PARTITION BY query_id ORDER BY n_obj, cell {_SUFFIX}) AS rest FROM qc{v} JOIN cs{v} USING (cell)) JOIN query_totals USING (query_id)),
gb{v} AS (SELECT object_id, cell, sum(w) OVER (PARTITION BY object_id ORDER BY n_obj, cell {_SUFFIX}) AS bound_r FROM oc{v} JOIN cs{v} USING (cell)),
gs{v} AS (SELECT r, query_id, object_id FROM gr{v} JOIN gb{v} USING (cell), (SELECT DISTINCT r FROM settings) WHERE 10000 * rest >= r * area AND 10000 * bound_r >= r * area)"""


_SWEPT_TOKENS = f""",
tr AS (SELECT query_id, token, w_total, rest FROM (SELECT *, sum(w) OVER (PARTITION BY query_id ORDER BY n_obj, token {_SUFFIX}) AS rest FROM query_tokens) JOIN query_totals USING (query_id)),
tb AS (SELECT object_id, token, sum(w) OVER (PARTITION BY object_id ORDER BY n_obj, token {_SUFFIX}) AS bound_t FROM signed),
ts AS (SELECT t, query_id, object_id FROM tr JOIN tb USING (token), (SELECT DISTINCT t FROM settings) WHERE 10000 * rest >= t * w_total AND 10000 * bound_t >= t * w_total)"""


def token_or_grid(kind: str, queries: str, levels, settings) -> str:
    head = parts(kind, queries, tuple(levels)) + _settings(settings) + _SWEPT_TOKENS + "".join(swept_grid(v) for v in levels)
    count = "CAST(sum(n) AS BIGINT) AS retrieved, count(*) AS candidates"
    rows = [f"SELECT 'token' AS method, -1 AS level, r AS tau_r_bp, t AS tau_t_bp, {count} FROM (SELECT t, query_id, object_id, count(*) AS n FROM ts GROUP BY ALL) JOIN settings USING (t) GROUP BY r, t"]
    rows += [f"SELECT 'grid', {v}, r, t, {count} FROM (SELECT r, query_id, object_id, count(*) AS n FROM gs{v} GROUP BY ALL) JOIN settings USING (r) GROUP BY r, t" for v in levels]
    return head + "\n" + " UNION ALL ".join(rows)


def grid_or_pair(kind: str, queries: str, levels, settings) -> str:
    head = parts(kind, queries, tuple(levels)) + _settings(settings) + _SWEPT_TOKENS + ",\ntc AS (SELECT t, query_id, object_id, count(*) AS n FROM ts GROUP BY ALL)" + "".join(swept_grid(v) + f",\ngc{v} AS (SELECT r, query_id, object_id, count(*) AS n FROM gs{v} GROUP BY ALL)" for v in levels)
    rows = []
    for v in levels:
        rows.append(f"SELECT 'grid' AS method, {v} AS level, r AS tau_r_bp, t AS tau_t_bp, CAST(sum(n) AS BIGINT) AS retrieved, count(*) AS candidates FROM gc{v} JOIN settings USING (r) GROUP BY r, t")
        rows.append(f"SELECT 'pair', {v}, s.r, s.t, CAST(sum(g.n * c.n) AS BIGINT), count(*) FROM settings s JOIN gc{v} g ON g.r = s.r JOIN tc c ON c.t = s.t AND c.query_id = g.query_id AND c.object_id = g.object_id GROUP BY s.r, s.t")
    return head + "\n" + " UNION ALL ".join(rows)


def comparison(kind: str, queries: str, settings, methods) -> str:
    names = ", ".join(f"'{m}'" for m in methods)
    return parts(kind, queries) + _settings(settings) + f""",
near AS (SELECT q.query_id, o.object_id, (least(q.x1, o.x1) - greatest(q.x0, o.x0)) * (least(q.y1, o.y1) - greatest(q.y0, o.y0)) AS inter FROM queries q JOIN objects o ON q.x0 < o.x1 AND o.x0 < q.x1 AND q.y0 < o.y1 AND o.y0 < q.y1),
alike AS (SELECT n.query_id, n.object_id, inter, q.area + o.area - inter AS union_area, q.w_total + o.w_total AS ws FROM near n JOIN query_totals q USING (query_id) JOIN totals o USING (object_id) WHERE 10000 * inter >= (SELECT min(r) FROM settings) * (q.area + o.area - inter)),
shared AS (SELECT a.query_id, a.object_id, any_value(inter) AS inter, any_value(union_area) AS union_area, any_value(ws) AS ws, CAST(sum(qt.w) AS BIGINT) AS iw FROM alike a JOIN object_tokens ot USING (object_id) JOIN query_tokens qt ON qt.query_id = a.query_id AND qt.token = ot.token GROUP BY a.query_id, a.object_id)
SELECT method, r AS tau_r_bp, t AS tau_t_bp, count(*) AS answers, CAST(sum(inter) AS BIGINT) AS inter_area, CAST(sum(iw) AS BIGINT) AS inter_w FROM shared, settings, (SELECT unnest([{names}]) AS method)
WHERE 10000 * inter >= r * union_area AND 10000 * iw >= t * (ws - iw) AND ws > iw GROUP BY method, r, t"""


def scaling(kind: str, queries: str, percents, t: int, r: int, v: int) -> str:
    """Each share of the objects has statistics of its own, so each is a query of its own."""
    one = lambda p: parts(kind, queries, (v,)).replace("object_tokens AS (", f"objects AS (SELECT * FROM all_objects WHERE (object_id * 7919 + 13) % 100 < {p}),\nobject_tokens AS (SELECT * FROM all_tokens WHERE (object_id * 7919 + 13) % 100 < {p}),\nall_tokens_ AS (").replace("\nobjects AS (SELECT object_id, min", "\nall_objects AS (SELECT object_id, min") + token_hits(t) + grid_hits(r, v)
    return " UNION ALL ".join("SELECT * FROM (" + _moved(one(p)) + "\n" + hits_row(f"{p} AS percent", f"th JOIN gh{v} USING (query_id, object_id)") + ")" for p in percents)


def _moved(sql: str) -> str:
    """The tokens of all objects come before those of a share."""
    a = sql.index("objects AS (SELECT * FROM all_objects")
    b = sql.index("all_tokens_ AS (", a)
    c = sql.index(",\nstats AS (", b) if ",\nstats AS (" in sql else sql.index(",stats", b)
    return sql[:a] + sql[b:c].replace("all_tokens_ AS (", "all_tokens AS (") + ",\n" + sql[a:b].rstrip(",\n") + sql[c:]


def hashed_pairs(kind: str, queries: str, r: int, t: int, v: int, buckets: int) -> str:
    """Candidates of the pair filter with a bucket limit: the larger of each bound stays where an object's pairs collide."""
    bucket = f"CAST('0x' || substr(md5(token || ':' || cell), 1, 8) AS BIGINT) % {buckets} AS bucket"
    return parts(kind, queries, (v,)) + token_hits(t) + grid_hits(r, v) + f""",
ob AS (SELECT object_id, {bucket}, max(bound_t) AS bound_t, max(bound_r) AS bound_r FROM tp JOIN cp{v} USING (object_id) GROUP BY ALL),
qb AS (SELECT DISTINCT query_id, {bucket}, w_total, area FROM qp JOIN qcp{v} USING (query_id))
SELECT DISTINCT query_id, object_id FROM qb JOIN ob USING (bucket) WHERE 10000 * bound_t >= {t} * w_total AND 10000 * bound_r >= {r} * area"""


def tree_visits(kind: str, queries: str, r: int, t: int, fanout: int = 32, most: int = 4) -> str:
    """Nodes visited on each level of the tree: objects ranked along the curve through their centres, ``fanout`` to a parent."""
    spread = lambda c: [f"(({c} << {s}) | {c}) & {m}" for s, m in ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555))]
    zx, zy = spread("cx"), spread("cy")
    steps = "".join(f"z{k + 1} AS (SELECT * REPLACE ({zx[k]} AS cx, {zy[k]} AS cy) FROM z{k}),\n" for k in range(4))
    sql = parts(kind, queries) + f""",
z0 AS (SELECT o.*, ((x0 + x1 - 2 * sx) >> 1) >> greatest(0, xb - 15) AS cx, ((y0 + y1 - 2 * sy) >> 1) >> greatest(0, yb - 15) AS cy FROM objects o, space),
{steps}placed AS (SELECT *, row_number() OVER (ORDER BY cx | (cy << 1), object_id) - 1 AS rank FROM z4),
tall AS (SELECT greatest(1, CAST(ceil(round(ln(count(*)) / ln({fanout}), 9)) AS INTEGER)) AS h FROM objects),
lv AS (SELECT unnest(range(0, {most} + 1)) AS level),
up AS (SELECT level, h, CASE WHEN level = 0 THEN object_id ELSE rank // CAST(pow({fanout}, level) AS BIGINT) END AS node_id, rank // CAST(pow({fanout}, least(level + 1, h)) AS BIGINT) AS parent_id, p.* FROM placed p, tall, lv WHERE level <= h),
nodes AS (SELECT level, h, node_id, parent_id, min(x0) AS x0, min(y0) AS y0, max(x1) AS x1, max(y1) AS y1 FROM up GROUP BY ALL),
nw AS (SELECT DISTINCT level, node_id, token FROM up JOIN object_tokens USING (object_id)),
ok AS (SELECT q.query_id, level, h, node_id, parent_id FROM nodes n JOIN queries q ON q.x0 < n.x1 AND n.x0 < q.x1 AND q.y0 < n.y1 AND n.y0 < q.y1 JOIN query_totals qt ON qt.query_id = q.query_id
  WHERE 10000 * (least(q.x1, n.x1) - greatest(q.x0, n.x0)) * (least(q.y1, n.y1) - greatest(q.y0, n.y0)) >= {r} * qt.area
    AND 10000 * coalesce((SELECT sum(w) FROM query_tokens x JOIN nw USING (token) WHERE x.query_id = q.query_id AND nw.level = n.level AND nw.node_id = n.node_id), 0) >= {t} * qt.w_total)"""
    for k in range(most, -1, -1):
        above = f" AND (level = h OR EXISTS (SELECT 1 FROM v{k + 1} p WHERE p.query_id = ok.query_id AND p.node_id = ok.parent_id))" if k < most else " AND level = h"
        sql += f",\nv{k} AS (SELECT query_id, node_id FROM ok WHERE level = {k}{above})"
    return sql + "\n" + " UNION ALL ".join(f"SELECT {k} AS level, count(*) AS visited FROM v{k} HAVING (SELECT h FROM tall) >= {k}" for k in range(most + 1))
