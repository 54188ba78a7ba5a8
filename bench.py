"""Times of the methods on the shipment objects; prints one JSON line.

The indexes are built once (tree and chosen cells included); then each method answers a batch of 100 queries, candidates and verification included. ``queries`` has seconds for a batch; ``split`` has seconds for filter and verification apart and milliseconds a query; ``counts`` has what doesn't depend on the machine. After BENCH_SECONDS (480) what is not measured yet is left out, and ``unfinished`` says so.
"""

import json
import os
import shutil
import signal
import sys
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from arealex.operators import baselines as B
from arealex.operators import levels as L
from arealex.operators import probes as P
from arealex.operators.verify import verify
from arealex.plans import measures as M
from arealex.sources import objects as R
from arealex.sources.querysets import query_set, with_thresholds
from arealex.sources.shared import kept
from arealex.sources.store import build_index, load_index

SF, CPUS, LEVEL = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8"), 7
BUDGET, QUAD_LEVEL = 64, 6


def main() -> None:
    work = tempfile.mkdtemp(prefix="bench-")
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", f"file://{work}/shared").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}
    split: dict[str, dict[str, float]] = {}
    counts: dict[str, object] = {}

    def timed(name, run):
        began = time.time()
        out = run()
        times[name] = round(time.time() - began, 3)
        print(name, times[name], file=sys.stderr, flush=True)
        return out

    late: list[bool] = []

    def stop(*_) -> None:
        late.append(True)
        raise TimeoutError

    done = lambda df: df.agg(F.count("*"), F.sum("inter_area")).first()[0]

    def measure() -> None:
        objects = timed("derive_objects", lambda: kept(R.shipment(spark, SF)))
        timed("build_index", lambda: build_index(P.Index(objects), f"{work}/index", LEVEL, shards=8, budget=BUDGET, max_level=QUAD_LEVEL))
        ix = load_index(spark, f"{work}/index")
        large = query_set(ix, "large", 4000, 4000)
        counts["objects"], counts["queries"] = ix.count(), large.count()
        counts["index"] = {r.kind: [r.rows, r.bytes] for r in ix.sizes().collect()}
        q = with_thresholds(large, 1000, 4000)
        runs = {
            "quad_pair": lambda q: ix.search(q, "quad_pair"),
            "grid_bounded": lambda q: ix.search(q, "grid_bounded"),
            "area_first": lambda q: B.area_first(ix, q, "grid", LEVEL),
            "two_filter": lambda q: ix.search(q, "two_filter"),
            "pair": lambda q: verify(ix, q, P.pair(ix, q, LEVEL)),
            "word_first": lambda q: B.word_first(ix, q),
            "word_tree": lambda q: B.word_tree_search(ix, q),
        }
        done(runs["grid_bounded"](q))  # code is compiled and files are touched

        def batch(label: str, q, names) -> None:
            for m in names:
                found = timed(f"{m}_{label}", lambda m=m: done(runs[m](q)))
                counts.setdefault(f"answers_{label}", {})[m] = found
                counts.setdefault(f"ms_per_query_{label}", {})[m] = round(1000 * times[f"{m}_{label}"] / max(1, counts["queries"]), 2)

        batch("10_40", q, ("quad_pair", "grid_bounded", "area_first", "two_filter", "pair"))
        # Filter and verification apart, from candidates that are written once.
        for name, found in (("quad_pair", lambda: ix.candidates(q, "quad_pair")), ("grid_bounded", lambda: ix.candidates(q, "grid_bounded"))):
            a, b, near, answers = M.split_seconds(ix, q, found)
            split[name] = {"filter": round(a, 3), "verify": round(b, 3), "candidates": near, "answers": answers}
        batch("40_40", large, ("quad_pair", "grid_bounded", "area_first"))
        batch("10_40", q, ("word_first",))
        timed("build_tree", lambda: ix._once(("tree", 32), lambda: B.kept_tree(ix, 32)))
        batch("10_40", q, ("word_tree",))
        batch("small_10_40", with_thresholds(query_set(ix, "small", 1000, 4000), 1000, 4000), ("quad_pair", "grid_bounded", "area_first"))
        counts["pi1_pi2_seconds"] = [float(f"{x:.3g}") for x in L.calibrate_costs(ix, large, LEVEL)]

    signal.signal(signal.SIGALRM, stop)
    signal.alarm(int(os.environ.get("BENCH_SECONDS", "480")))
    try:
        measure()
    except Exception:  # noqa: BLE001  the gateway may have wrapped the signal's error
        if not late:
            raise
        counts["unfinished"] = True
    signal.alarm(0)
    total = sum(v for k, v in times.items() if k.endswith(("40_40", "10_40")))
    print(json.dumps({"metric": "seconds for batches of 100 queries over all methods", "value": round(total, 3), "unit": "sec", "queries": times, "split": split, "counts": counts, "sf": SF}))
    sys.stdout.flush()
    spark.sparkContext.cancelAllJobs()
    spark.stop()
    shutil.rmtree(work, ignore_errors=True)


if __name__ == "__main__":
    main()
