"""The worked example, losslessness on random data, and odd inputs."""

import math
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from arealex.functions.cells import Space, bounding_space, cells_of
from arealex.operators import baselines as B
from arealex.operators import counting as C
from arealex.operators import levels as L
from arealex.operators import linking as K
from arealex.operators import probes as P
from arealex.operators import quadcells as Q
from arealex.operators import signatures as S
from arealex.operators.verify import exact_scan, verify
from arealex.plans import search as X
from arealex.plans import workloads as W
from arealex.sources import objects as R
from arealex.sources.querysets import with_thresholds
from arealex.sources.store import build_index, describe_index, load_index

QUERY = "query_id bigint, x0 bigint, y0 bigint, x1 bigint, y1 bigint, tokens array<string>, tau_r_bp bigint, tau_t_bp bigint"


@pytest.fixture(scope="module")
def example(spark):
    return R.worked_example(spark)


def ids(df):
    return {r.object_id for r in df.collect()}


def test_worked_example(spark, example):
    objects, q = example
    ix = P.Index(objects)
    stats = {r.token: r for r in ix.stats.collect()}
    assert [stats[t].w for t in ("t1", "t2", "t4")] == [round(math.log(7 / k) * 1e6) for k in (3, 5, 2)]
    assert {r.token: r.n_obj for r in ix.stats.collect()} == {"t1": 3, "t2": 5, "t3": 3, "t4": 2, "t5": 2}
    found = X.search(ix, q).collect()
    assert [(r.object_id, r.inter_area, r.union_area) for r in found] == [(2, 1000, 3150)]
    assert ids(P.token_overlap(ix, q)) == {1, 2, 3, 4, 5} == ids(P.token_bounded(ix, q))
    assert {r.token for r in P.token_prefix(ix, q).collect()} == {"t1", "t3"}
    one = exact_scan(ix, with_thresholds(q, 1, 1)).where("object_id = 1").first()
    assert (one.inter_area, one.union_area) == (1000, 4400) and round(one.inter_w / one.union_w, 2) == 0.58


def test_worked_example_on_its_own_grid(spark, example):
    """Cells of side 30 become cells of side 2**20 when sides are stretched; cell edges stay exact, areas are off by rounding only."""
    objects, q = example
    wide = lambda df: df.select(*[F.round(F.col(c) * (2.0**20 / 30)).cast("bigint").alias(c) if c in R.SIDES else F.col(c) for c in df.columns])
    ix, batch, unit = P.Index(wide(objects), space=Space(0, 0, 22, 22)), wide(q), 2.0**40 / 900
    sums = {r.object_id: r.shared / unit for r in P.grid_overlap(ix, with_thresholds(batch, 1, 1), 2).collect()}
    assert sums[2] == pytest.approx(1375, abs=0.1)
    assert P.cell_prefix(ix, batch, 2).count() == 4
    # Ties in the order of cells are broken by our code, not row by row, so one posting more is retrieved.
    assert P.grid_bounded_hits(ix, batch, 2).count() in (6, 7) and ids(P.grid_bounded(ix, batch, 2)) == {1, 2, 5, 7}
    assert ids(P.pair(ix, batch, 2)) == {1, 2, 5} == ids(P.two_filter(ix, batch, 2))
    assert ids(X.search(ix, batch, "pair", level=2)) == {2}
    prefix = P.cell_prefix(ix, batch, 2).select("cell")
    bounds = [(r.object_id, round(r.bound_r / unit)) for r in ix.cells(2).join(prefix, "cell", "left_semi").collect()]
    assert (1, 900) in bounds


def brute(objects, queries, n=None):
    count = {}
    for *_, tokens in objects:
        for t in set(tokens):
            count[t] = count.get(t, 0) + 1
    weight = lambda t: round(math.log(len(objects) / count.get(t, 1)) * 1e6)
    out = set()
    for qi, ax0, ay0, ax1, ay1, at, tr, tt in queries:
        for oi, bx0, by0, bx1, by1, bt in objects:
            inter = max(0, min(ax1, bx1) - max(ax0, bx0)) * max(0, min(ay1, by1) - max(ay0, by0))
            union = (ax1 - ax0) * (ay1 - ay0) + (bx1 - bx0) * (by1 - by0) - inter
            wi, wu = sum(map(weight, set(at) & set(bt))), sum(map(weight, set(at) | set(bt)))
            if (tr <= 0 or union > 0 and 10000 * inter >= tr * union) and (tt <= 0 or wu > 0 and 10000 * wi >= tt * wu):
                out.add((qi, oi))
    return out


def random_data(seed, n=80, nq=14):
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(9)]

    def rect():
        x, y = rng.randrange(-20, 90), rng.randrange(-20, 90)
        return x, y, x + rng.choice((0, 1, 5, 8, 16, 40)), y + rng.choice((0, 1, 5, 8, 16, 40))

    objects = [(k, *rect(), ["everywhere", *rng.sample(words, rng.randrange(0, 5))]) for k in range(n)]
    objects += [(n + k, *objects[k][1:]) for k in range(8)]
    queries = []
    for k in range(nq):
        base = rng.choice(objects)
        queries.append((k, *(base[1:5] if rng.random() < 0.6 else rect()), [*base[5][:3], *(["unseen"] if k % 3 == 0 else [])], rng.choice((0, 1, 2500, 5000, 10000)), rng.choice((0, 1, 2500, 5000, 10000))))
    queries.append((99, 500, 500, 600, 600, ["w1"], 1000, 1000))
    return objects, queries


def frames(spark, objects, queries):
    return spark.createDataFrame(objects, R.SCHEMA), spark.createDataFrame(queries, QUERY)


@pytest.mark.parametrize("method,options", [("two_filter", {"level": 3}), ("pair", {"level": 3, "buckets": 1}), ("quad_pair", {"budget": 10, "max_level": 3}), ("word_first", {}), ("area_first", {"level": 3}), ("token_bounded", {})])
def test_methods_lose_nothing(spark, method, options):
    objects, queries = random_data(1)
    o, q = frames(spark, objects, queries)
    got = {(r.query_id, r.object_id) for r in X.search(P.Index(o), q, method, **options).collect()}
    want = brute(objects, queries)
    assert got == want


def test_tree_and_filters_agree_on_positive_thresholds(spark):
    objects, queries = random_data(2)
    queries = [(*x[:6], max(x[6], 1), max(x[7], 1)) for x in queries]
    o, q = frames(spark, objects, queries)
    ix, want = P.Index(o), brute(objects, queries)
    for pairs in (B.word_tree_candidates(ix, q, fanout=3), P.signature_scan(ix, q), P.grid_overlap(ix, q, 4), P.size_filter(ix, q, P.two_filter(ix, q, 4))):
        assert {(r.query_id, r.object_id) for r in verify(ix, q, pairs).collect()} == want
    grid, token = ({(r.query_id, r.object_id) for r in f.collect()} for f in (P.grid_bounded(ix, q, 4), P.token_bounded(ix, q)))
    both = {(r.query_id, r.object_id) for r in P.pair(ix, q, 4).collect()}
    hashed = {(r.query_id, r.object_id) for r in P.pair(ix, q, 4, 7).collect()}
    assert both == grid & token <= hashed


def test_cells_cover_rectangles(spark):
    objects, _ = random_data(3)
    o = spark.createDataFrame(objects, R.SCHEMA)
    space = bounding_space(o)
    areas = {k: (x1 - x0) * (y1 - y0) for k, x0, y0, x1, y1, _ in objects}
    for level in (0, 2, 5, 9):
        sums = {r.object_id: r.s for r in cells_of(o, space, level, "object_id").groupBy("object_id").agg(F.sum("w").alias("s")).collect()}
        assert sums == {k: v for k, v in areas.items() if v}


def test_greedy_cells_and_optimum(spark):
    objects, _ = random_data(4, n=60)
    ix = P.Index(spark.createDataFrame(objects, R.SCHEMA))
    depth = 3
    cells = Q.cell_error(ix, Q.token_cells(ix, depth), depth, "finest").toPandas()

    def best(size, node, m):
        """Least error of at most m leaves below a node."""
        level, cell = node
        here = size.get(node, 0.0)
        if m < 4 or level == depth:
            return here
        kids = [(level + 1, 4 * cell + k) for k in range(4)]
        table = {0: 0.0}
        for i, kid in enumerate(kids):
            table = {a + b: min((table[x] + best(size, kid, y) for x in table for y in range(1, m - 2 - i + i) if x + y == a + b), default=1e18) for a in table for b in range(1, m - 2)}
        return min(here, *(v for k, v in table.items() if k <= m))

    for token in ("everywhere", "w1"):
        own = cells[cells.token == token]
        size = {(v, c): e for v, c, e in zip(own.level, own.cell, own.error, strict=True)}
        totals = []
        for budget in (1, 4, 7):
            chosen = Q.greedy_cells(own, budget, depth, True)
            assert len(chosen) <= budget
            assert sum(4.0 ** -v for v, _, _ in chosen) == 1.0
            totals.append(sum(size.get((v, c), 0.0) for v, c, _ in chosen))
            assert totals[-1] >= best(size, (0, 0), budget) - 1e-6
        assert totals == sorted(totals, reverse=True)


def test_level_walk(spark):
    objects, queries = random_data(5)
    o, q = frames(spark, objects, [(*x[:6], 4000, 4000) for x in queries])
    costs = L.expected_level_cost(P.Index(o), q, [0, 1, 2, 3, 4])
    rows = {r.level: r.benefit for r in L.level_benefits(costs).collect()}
    assert L.pick_level(costs, 1e9).first().level == 0
    want = min((v for v, b in rows.items() if b is not None and b < 1.0), default=4)
    assert L.pick_level(costs, 1.0).first().level == want
    assert L.best_level(costs).first().cost == min(r.cost for r in costs.collect())


def test_empty_and_single(spark):
    none, q = frames(spark, [], [(1, 0, 0, 4, 4, ["a"], 1000, 1000)])
    assert X.search(P.Index(none), q).count() == 0
    one, _ = frames(spark, [(7, 0, 0, 4, 4, ["a"])], [])
    # With one object its token has weight 0, so only a word threshold of 0 lets it through.
    assert X.search(P.Index(one), q).count() == 0
    assert ids(X.search(P.Index(one), with_thresholds(q, 10000, 0))) == {7}


def test_validation(spark):
    rows = spark.createDataFrame([(1, 0, 0, 2, 2, ["a", "a", None], "x"), (None, 0, 0, 1, 1, [], "y"), (3, 5, 0, 1, 1, None, "z")], R.SCHEMA + ", more string")
    got = R.validated(rows).collect()
    assert [(r.object_id, r.tokens) for r in got] == [(1, ["a"])]
    with pytest.raises(ValueError):
        R.validated(rows.drop("tokens"))


def test_files(spark, tmp_path, example):
    objects, _ = example
    objects.write.json(str(tmp_path / "j"))
    objects.withColumn("tokens", F.array_join("tokens", " ")).write.option("header", True).csv(str(tmp_path / "c"))
    for kind in ("json", "csv"):
        assert sorted(map(str, R.from_file(spark, str(tmp_path / kind[0]), kind).collect())) == sorted(map(str, objects.collect()))


def test_store(spark, tmp_path):
    objects, queries = random_data(6)
    queries = [(*x[:6], max(x[6], 1000), max(x[7], 1000)) for x in queries]
    o, q = frames(spark, objects, queries)
    want = brute(objects, queries)
    for k, least in enumerate((0, 1000)):
        path = str(tmp_path / f"i{k}")
        build_index(P.Index(o), path, level=3, shards=4, min_tau_r_bp=least, min_tau_t_bp=least)
        ix = load_index(spark, path)
        assert {(r.query_id, r.object_id) for r in ix.search(q).collect()} == want
        assert describe_index(spark, path).first().objects_rows == len(objects)
    with pytest.raises(ValueError):
        ix.search(with_thresholds(q, 10, 10))
    ix.append(spark.createDataFrame([(1000, *objects[0][1:])], R.SCHEMA))
    again = {(r.query_id, r.object_id) for r in load_index(spark, path).search(q).collect()}
    assert {(a, 1000) for a, b in want if b == 0} <= again


def test_sql_functions(spark):
    X.register_sql(spark)
    r = spark.sql("SELECT overlap_area(35, 50, 75, 110, 0, 70, 60, 120) AS o, round(region_jaccard(35, 50, 75, 110, 0, 70, 60, 120), 4) AS j").first()
    assert (r.o, r.j) == (1000, 0.2273)


def test_self_search_and_orders(spark):
    objects, _ = random_data(7, n=50)
    o = spark.createDataFrame(objects, R.SCHEMA)
    links, owner = X.class_links(P.Index(o), 2500, 2500, 3)
    classes = {r.object_id: r.class_id for r in owner.collect()}
    got = {(r.a, r.b) for r in links.collect()}
    want = brute(objects, [(*x, 2500, 2500) for x in objects])
    assert {(classes[a], classes[b]) for a, b in want if classes[a] < classes[b]} == got
    assert set(S.ORDERS) == {"rare", "frequent", "random", "code"}


@pytest.mark.parametrize("measure,block", [("jaccard", 2048), ("jaccard", 7), ("dice", 7)])
def test_links_counted_in_tasks_are_those_of_the_pairs(spark, measure, block, monkeypatch):
    """Each link counts once, however many tokens and cells two objects share, in long lists and short ones; no pair leaves a task."""
    rng = random.Random(3)
    rows = []
    for k in range(240):
        x, y, w, h = rng.randrange(400), rng.randrange(400), rng.choice([0, 3, 60, 250]), rng.choice([1, 40, 300])
        rows.append((k, x, y, x + w, y + h, [f"w{t}" for t in rng.sample(range(12), rng.randrange(7))]))
    rows += [(k + 500, *r) for k, *r in rows[::9]] + [(900, 0, 0, 9, 9, None)]
    ix = P.Index(spark.createDataFrame(rows, R.SCHEMA), measure, measure)
    monkeypatch.setattr(K, "BLOCK", block)
    monkeypatch.setattr(K, "PAIRS", 50)
    got = {r.object_id: (r.class_id, r.n_links) for r in X.self_search(ix, 1000, 2000, 4).collect()}
    links, owner = X.class_links(ix, 1000, 2000, 4)
    n = Counter(x for r in links.collect() for x in (r.a, r.b))
    assert got == {r.object_id: (r.class_id, n[r.class_id]) for r in owner.collect()} and sum(n.values()) > 300 and len(got) == len(rows)
    plan = X.self_search(ix, 1000, 2000, 4)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "other" not in plan


def test_words_of_a_document_stay_in_its_row(spark, tmp_path):
    """As the SQL has them, also for rows that share an id, without text or without words; texts with an id of their own make no row for a word."""
    import duckdb

    from arealex import queries as own

    texts = ["B a b, c\u00c9 a d b", "one one TWO two x y z " + " ".join(f"q{chr(97 + k)}" for k in range(20)), "  ?! 12", None, "x"]
    rows = [(k, t, f"src{k}", k) for k, t in enumerate(texts)] + [(7, "a b b", "src7", 1), (7, "c c c b", "src7", 1)]
    spark.createDataFrame(rows, "doc_id bigint, text string, source string, n bigint").write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    got = {r.object_id: r.tokens for r in own.QUERIES["objects_document"](spark, str(tmp_path)).collect()}
    assert got == {k: t for k, *_, t in con.execute(own.ORACLE_SQL["objects_document"]).fetchall() if k != 7} | {7: "a b c"}
    plan = R.document(spark, str(tmp_path))._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and plan.count("Generate") == 1


def test_standing_queries(spark, tmp_path, example):
    from arealex.streaming.windows import standing_matches

    objects, q = example
    objects.withColumn("user_id", F.col("object_id")).withColumn("start", F.lit(0).cast("bigint")).drop("object_id").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("x0 bigint, y0 bigint, x1 bigint, y1 bigint, tokens array<string>, user_id bigint, start bigint").parquet(str(tmp_path / "in"))
    standing_matches(stream, P.Index(objects), q, str(tmp_path / "out"), str(tmp_path / "state")).awaitTermination()
    found = spark.read.parquet(str(tmp_path / "out")).collect()
    assert [(r.query_id, r.inter_area) for r in found] == [(1, 1000)]


def test_stored_chosen_cells(spark, tmp_path):
    objects, queries = random_data(8)
    queries = [(*x[:6], max(x[6], 1000), max(x[7], 1000)) for x in queries]
    o, q = frames(spark, objects, queries)
    build_index(P.Index(o), str(tmp_path / "i"), level=3, shards=3, budget=10, max_level=3)
    ix = load_index(spark, str(tmp_path / "i"))
    for method in ("auto", "quad_pair", "grid_bounded", "two_filter"):
        assert {(r.query_id, r.object_id) for r in ix.search(q, method).collect()} == brute(objects, queries)
    sizes = {r.kind: (r.rows, r.bytes) for r in ix.sizes().collect()}
    assert set(sizes) == {"objects", "stats", "cell_stats", "token", "cell", "selection", "quad"} and all(b > 0 for _, b in sizes.values())
    ix.append(spark.createDataFrame([(1000, *objects[0][1:])], R.SCHEMA))
    again = {(r.query_id, r.object_id) for r in load_index(spark, str(tmp_path / "i")).search(q, "quad_pair").collect()}
    assert {(a, 1000) for a, b in brute(objects, queries) if b == 0} <= again


def test_axis_and_key_limits(spark):
    rows = [(1, 0, 0, 1 << 26, 1 << 26, ["a"])]
    with pytest.raises(ValueError):
        P.Index(spark.createDataFrame(rows, R.SCHEMA))
    assert R._room(100, 29, 10**6) == 100 and R._room(100, 100, 10**6) == 1000
    with pytest.raises(ValueError):
        R._room(1_000_000, 5, 10**13)


def test_exact_cells_and_windows(spark):
    from arealex.streaming.windows import windowed_objects

    objects, queries = random_data(9, n=60)
    o, q = frames(spark, objects, [(*x[:6], 1000, 1000) for x in queries])
    ix = P.Index(o)
    for level in (0, 3, 6):
        # On any level the exact weights of cells add up to the overlap.
        sums = {(r.query_id, r.object_id): r.shared for r in P.grid_overlap(ix, q, level, "exact").collect()}
        boxes, mine = {x[0]: x[1:5] for x in objects}, {x[0]: x[1:5] for x in queries}
        for (a, b), s in sums.items():
            u, v = mine[a], boxes[b]
            assert s == max(0, min(u[2], v[2]) - max(u[0], v[0])) * max(0, min(u[3], v[3]) - max(u[1], v[1]))
    events = spark.createDataFrame([(k, f"2024-01-0{1 + k // 4} 0{k % 4}:30:00", 7, "view", 1.5 + k, '{"k": 12}') for k in range(8)], "event_id bigint, ts string, user_id bigint, event_type string, value double, props string")
    assert windowed_objects(events, "1 day").count() == 2
    assert windowed_objects(events, "1 day", "12 hours").count() == 4
    assert windowed_objects(events, session_gap="90 minutes").count() == 2


def test_exploded_rows_are_not_broadcast(spark, example):
    """Cells of objects are far more rows than the objects by whose size the planner guesses."""
    ix = P.Index(example[0])
    for level in (6, 8):
        plan = ix.cells(level)._jdf.queryExecution().sparkPlan().toString()
        assert ("BroadcastHashJoin" in plan) == (level <= S.BROADCAST_LEVEL) and "BuildLeft" not in plan


def test_grid_probe_of_some_objects_keeps_all_hits(spark):
    """Objects out of reach are left out before bounds are made; the hits are those of all objects."""
    rng = random.Random(3)
    rows = [(k, x, y, x + rng.randint(1, 300), y + rng.randint(1, 300), ["a", f"t{k % 5}"]) for k in range(300) for x, y in [(rng.randrange(4000), rng.randrange(4000))]]
    ix = P.Index(spark.createDataFrame(rows, R.SCHEMA))
    q = spark.createDataFrame([(k, x, y, x + 200, y + 250, ["a", "t1"], 2000, 1000) for k, (x, y) in enumerate([(100, 100), (2000, 3000), (3500, 400)])], QUERY)
    for level in (3, 6):
        some = P.near(ix, q, level)
        assert some.objects.count() < 150
        p = P.cell_prefix(ix, q, level).drop("w", "n_obj")
        want = ix.cells(level).join(p, "cell").where(P._enough_r(ix, "bound_r"))
        pairs = lambda df: sorted((r.query_id, r.object_id, r.cell) for r in df.collect())
        assert pairs(P.grid_bounded_hits(P.Index(ix.objects), q, level)) == pairs(want) != []


def test_shipments_with_long_part_keys_follow_their_sql(spark, tmp_path):
    """Part keys from a million on: objects, their statistics and areas are those of the SQL, whose key lets two of them fall together."""
    import datetime

    import duckdb

    from arealex import queries as own

    day, d = datetime.date(1996, 1, 1), str(tmp_path)
    lines = [(1, 1_000_007, 5.0, 900.4, 0.05, 0.02), (2, 7, 9.0, 1200.0, 0.0, 0.04), (2, 1_000_008, 1.0, 50.0, 0.1, 0.0), (3, 9, 2.0, 10.0, 0.1, 0.0)]
    spark.createDataFrame([(*x, day, "R", "F") for x in lines], "l_orderkey bigint, l_partkey bigint, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_shipdate date, l_returnflag string, l_linestatus string").coalesce(1).write.parquet(f"{d}/lineitem.parquet")
    spark.createDataFrame([(p, f"red w{p % 5}", "b1", "t1", 12) for p in (7, 9, 1_000_007, 1_000_008)], "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int").coalesce(1).write.parquet(f"{d}/part.parquet")
    spark.createDataFrame([(o, 1, "HIGH", "O") for o in (1, 2, 3)], "o_orderkey bigint, o_custkey bigint, o_orderpriority string, o_orderstatus string").coalesce(1).write.parquet(f"{d}/orders.parquet")
    spark.createDataFrame([(1, "BUILDING", 3)], "c_custkey bigint, c_mktsegment string, c_nationkey int").coalesce(1).write.parquet(f"{d}/customer.parquet")
    con = duckdb.connect()
    for t in ("lineitem", "part", "orders", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet/*.parquet'")
    for name in ("objects_shipment", "dataset_stats_shipment", "token_stats_shipment", "area_distribution_shipment", "grid_signature_shipment_l6"):
        assert sorted(map(tuple, own.QUERIES[name](spark, d).collect())) == sorted(con.execute(own.ORACLE_SQL[name]).fetchall()), name
    assert R.shipment(spark, d).count() == 3 and R.shipment(spark, d, apart=True).count() == 4


def test_counts_of_cells_without_a_row_for_each(spark):
    rng = random.Random(5)
    rows = [(k, x, y, x + rng.randint(0, 900), y + rng.randint(0, 900), ["a"]) for k in range(200) for x, y in [(rng.randrange(4000), rng.randrange(4000))]]
    ix = P.Index(spark.createDataFrame(rows, R.SCHEMA))
    for level in (0, 5):
        want = {tuple(r) for r in S.cell_stats(S.grid_signature(ix.objects, ix.space, level)).collect()}
        assert {tuple(r) for r in S.cell_counts(ix.objects, ix.space, level).collect()} == want


def test_worked_example_query_reads_a_table(spark):
    import duckdb

    from arealex import queries as own

    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{d}/events.parquet'")
    assert any("events.parquet" in f for f in R.first_users(spark, d).inputFiles())
    assert sorted(map(tuple, own.QUERIES["worked_example"](spark, d).collect())) == sorted(con.execute(own.ORACLE_SQL["worked_example"]).fetchall()) != []


@pytest.mark.parametrize("measure", ["jaccard", "cosine"])
def test_postings_counted_in_tasks_are_those_of_the_probes(spark, measure, monkeypatch):
    rng = random.Random(5)

    def row(k):
        x, y, w, h = rng.randrange(500), rng.randrange(500), rng.choice([0, 1, 9, 60, 400]), rng.choice([1, 7, 80, 500])
        return (k, x, y, x + w, y + h, [f"w{t}" for t in rng.sample(range(9), rng.randrange(6))])

    ix = P.Index(spark.createDataFrame([row(k) for k in range(150)], R.SCHEMA), measure, measure)
    # Queries reach over the space, lie outside of it, have no words, unknown ones or no area.
    own = [row(k)[:6] for k in range(12)] + [(12, -50, -50, 700, 300, ["w1", "new"]), (13, 5000, 5000, 5100, 5100, ["w1"]), (14, 3, 3, 3, 9, [])]
    q = P.known_size(spark.createDataFrame([(*r, 4000, 4000) for r in own], QUERY))
    settings = ((1000, 4000), (4000, 1000))
    monkeypatch.setattr(C, "ROWS", 40)
    assert C.fits(ix, q, [6])
    got = {(r.method, r.level, r.tau_r_bp, r.tau_t_bp): (r.retrieved, r.candidates) for r in C.retrieved(ix, q, ("token", "grid", "pair"), [6], settings).collect()}
    assert len(got) == 6
    for r, t in settings:
        own = with_thresholds(q, r, t)
        hits = {("token", -1): P.token_bounded_hits(ix, own), ("grid", 6): P.grid_bounded_hits(ix, own, 6), ("pair", 6): P.pair_hits(ix, own, 6)}
        for key, h in hits.items():
            assert got[*key, r, t] == tuple(W._row(h).first()), (key, r, t)
    assert got["grid", 6, 1000, 4000][0] > 1000


def test_filter_workloads_make_no_row_for_a_posting(spark):
    """What a sweep retrieves is counted where the objects are read: no join of postings, whose number is that of the pairs."""
    ix = P.Index(R.activity(spark, "/root/testdata/sf0.001"))
    settings = ((1000, 4000), (4000, 1000))
    for found in (W.token_or_grid(ix, "large", [4], settings), W.grid_or_pair(ix, "small", [4], settings), W.granularity(ix, "large", [4])):
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "Join" not in plan and "Generate" not in plan


def test_comparison_asks_a_sweep_once(spark, monkeypatch):
    """Each query is asked at the least thresholds of both sweeps, and every setting has the answers of its own thresholds."""
    ix = P.Index(R.activity(spark, "/root/testdata/sf0.001"))
    settings, asked, search = ((1000, 4000), (3000, 4000), (4000, 1000), (4000, 4000)), [], X.search
    monkeypatch.setattr(X, "search", lambda ix, q, m: asked.append({(r.tau_r_bp, r.tau_t_bp) for r in q.collect()}) or search(ix, q, m))
    found = {(r.tau_r_bp, r.tau_t_bp): (r.answers, r.inter_area, r.inter_w) for r in W.comparison(ix, "large", settings, ("exact_scan",)).collect()}
    assert asked == [{(1000, 4000), (4000, 1000)}]
    q = W.query_set(ix, "large", 4000, 4000)
    for r, t in settings:
        own = exact_scan(ix, P.known_size(with_thresholds(q, r, t))).agg(F.count("*"), F.sum("inter_area"), F.sum("inter_w")).first()
        assert found[r, t] == tuple(own)
    assert found[1000, 4000][0] > found[4000, 4000][0]


def test_counts_of_an_empty_table_are_zero(spark, tmp_path):
    spark.createDataFrame([], R.SCHEMA).write.parquet(f"{tmp_path}/none")
    ix = P.Index(spark.read.schema(R.SCHEMA).parquet(f"{tmp_path}/none"))
    q = P.known_size(spark.createDataFrame([(1, 0, 0, 9, 9, ["a"], 4000, 4000)], QUERY))
    assert [tuple(r) for r in C.retrieved(ix, q, ("grid",), [3], ((4000, 4000),)).collect()] == [("grid", 3, 4000, 4000, 0, 0)]


@pytest.mark.parametrize("measure", ["jaccard", "dice"])
def test_chosen_cells_counted_in_tasks_are_those_of_the_probe(spark, measure, monkeypatch):
    """Sums by token and cell, and what pairs of a token and its own cells retrieve, without a row for an object's token and cell."""
    rng = random.Random(8)

    def row(k):
        x, y, w, h = rng.randrange(500), rng.randrange(500), rng.choice([0, 1, 9, 60, 400]), rng.choice([1, 7, 80, 500])
        return (k, x, y, x + w, y + h, [f"w{t}" for t in rng.sample(range(9), rng.randrange(6))])

    ix = P.Index(spark.createDataFrame([row(k) for k in range(150)] + [(900, 0, 0, 9, 9, None)], R.SCHEMA), measure, measure)
    q = P.known_size(spark.createDataFrame([(*r, 2000, 2000) for r in [row(k)[:6] for k in range(12)] + [(12, -50, -50, 700, 300, ["w1", "new"]), (13, 5000, 5000, 5100, 5100, ["w1"]), (14, 3, 3, 3, 9, [])]], QUERY))
    monkeypatch.setattr(C, "ROWS", 40)
    for held, names in ((60, 4), (2_000_000, 100_000)):
        monkeypatch.setattr(C, "HELD", held)
        monkeypatch.setattr(C, "VOCABULARY", names)
        cells = Q.token_cells(ix, 4)
        want = Counter()
        for v in range(5):
            for r in cells_of(ix.objects, ix.space, v, "object_id", "tokens").collect():
                for t in r.tokens or []:
                    want[t, v, r.cell, "n"] += 1
                    want[t, v, r.cell, "w"] += r.w
        found = cells.collect()
        assert {(r.token, r.level, r.cell, c): x for r in found for c, x in (("n", r.n_obj), ("w", r.covered))} == want
        assert all(n not in cells._jdf.queryExecution().executedPlan().toString() for n in ("Generate", "Join"))
    selection = W.kept(Q.pick_quad_cells(ix, 12, 4))
    got = C.quad_retrieved(ix, q, selection, (2000, 2000))
    assert tuple(got.first()) == tuple(W._row(Q.quad_hits(ix, q, selection, 4)).first())
    assert got.first().retrieved > 100 and "Join" not in got._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("measure", ["jaccard", "dice"])
def test_words_first_makes_no_row_for_a_shared_token(spark, measure, monkeypatch):
    """A small batch's word sums are made inside tasks, in groups of any size, and the answers are those of a scan, also for duplicate and unknown words."""
    objects, queries = random_data(6)
    queries = [(*x[:6], max(x[6], 1), max(x[7], 1)) for x in queries]
    queries += [(100 + x[0], *x[1:6], 1, 1) for x in queries] + [(300, 0, 0, 9, 9, [], 1, 1), (301, 0, 0, 9, 9, ["unseen"], 1, 1)]
    o, q = frames(spark, objects + [(900, 0, 0, 9, 9, None), (901, 0, 0, 9, 9, [])], queries)
    want = sorted(map(tuple, exact_scan(P.Index(o, measure, measure), q).collect()))
    monkeypatch.setattr(P, "token_overlap", None)
    assert len(want) > 20
    for rows in (4096, 7):
        monkeypatch.setattr(C, "ROWS", rows)
        assert sorted(map(tuple, X.search(P.Index(o, measure, measure), q, "word_first").collect())) == want


def test_shipments_of_bits_are_those_of_strings(spark, tmp_path, monkeypatch):
    """Repeated part and order keys, parts without a name, missing words, part keys on both sides of a million and below 0."""
    import datetime

    rng = random.Random(3)
    for case, keys in (("short", [1, 2, 3, 4]), ("long", [1, 2, 1_000_001, 1_000_003, 999_999]), ("below", [-5, 1, 999_995])):
        d = f"{tmp_path}/{case}"
        lines = [(rng.randrange(1, 6), rng.choice([*keys, 77]), rng.choice([None, 5.0, 9.0]), rng.uniform(10, 2000), 0.05, 0.02, datetime.date(1996, 1, rng.randrange(1, 28)), rng.choice(["R", "N", None]), "F") for _ in range(60)]
        spark.createDataFrame(lines, "l_orderkey bigint, l_partkey bigint, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_shipdate date, l_returnflag string, l_linestatus string").write.parquet(f"{d}/lineitem.parquet")
        parts = [(p, rng.choice([None, f"red  w{p % 5}", "blue"]), rng.choice(["b1", None]), "t1", rng.choice([12, None])) for p in [*keys, *keys]]
        spark.createDataFrame(parts, "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int").write.parquet(f"{d}/part.parquet")
        spark.createDataFrame([(o, rng.randrange(1, 4), rng.choice(["HIGH", None]), rng.choice("OF")) for o in (1, 2, 2, 3, 4)], "o_orderkey bigint, o_custkey bigint, o_orderpriority string, o_orderstatus string").write.parquet(f"{d}/orders.parquet")
        spark.createDataFrame([(1, "BUILDING", 3), (2, None, None), (2, "AUTO", 7)], "c_custkey bigint, c_mktsegment string, c_nationkey int").write.parquet(f"{d}/customer.parquet")
        rows = lambda: sorted((r.object_id, str((*r[1:5], sorted(r.tokens)))) for r in R.shipment(spark, d).collect())
        found = rows()
        monkeypatch.setattr(R, "BIT_WORDS", 0)
        assert found == rows() and len(found) > 5
        monkeypatch.setattr(R, "BIT_WORDS", 504)


def test_candidates_found_inside_tasks_are_those_of_the_joins(spark, monkeypatch):
    """Each query at its own thresholds: two-sided filter, pairs, chosen cells and areas; with areas tested inside tasks the answers stay. No posting has a row of its own."""
    objects, queries = random_data(8)
    queries = [(*x[:6], max(x[6], 1), max(x[7], 1)) for x in queries]
    o, q = frames(spark, objects + [(900, 0, 0, 9, 9, None)], queries)
    ix = P.Index(o)
    selection = Q.pick_quad_cells(ix, 8, 3)
    found = lambda: [P.two_filter(ix, q, 3), P.pair(ix, q, 3), Q.quad_pair(ix, q, selection, 3), B.near_areas(ix, q, level=3)]
    mine = found()
    for f in mine:
        plan = f._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "Join" not in plan
    mine = [sorted(map(tuple, f.collect())) for f in mine]
    want = sorted(map(tuple, exact_scan(P.Index(o), q).collect()))
    for method in ("two_filter", "pair", "quad_pair", "area_first", "word_tree"):
        assert sorted(map(tuple, X.search(ix, q, method).collect())) == want and len(want) > 10
    monkeypatch.setattr(C, "fits", lambda *a: False)
    monkeypatch.setattr(C, "sums_fit", lambda *a: False)
    assert [sorted(map(tuple, f.collect())) for f in found()] == mine and all(map(len, mine))
