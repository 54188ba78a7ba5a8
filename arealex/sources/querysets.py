"""Query batches made of objects: large and small ones, at even steps of the rank by area."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from arealex.functions.similarity import SIDES, area, box
from arealex.operators import probes as P
from arealex.operators.baselines import ranked

THRESHOLDS = ((1000, 1000), (1000, 4000), (4000, 1000), (2000, 2000), (2500, 3000), (4000, 4000), (5000, 5000))
LEAST_AREA, WORDS = 64, 7


def query_set(ix: P.Index, kind: str, tau_r_bp: int, tau_t_bp: int, most: int = 100) -> DataFrame:
    """Up to ``most`` queries. *large*: seeds from the quarter of largest areas, each side pushed out by a sixteenth, with the heaviest tokens. *small*: from the quarter of smallest areas, pulled in, with all tokens. The batch is a local relation."""
    large = kind == "large"
    seeds = ix.objects.withColumn("_area", area(box())).where(F.col("_area") >= LEAST_AREA)
    n = seeds.count()
    step, upto = max(1, n // 400), n // 4
    keys = seeds.select("object_id", (-F.col("_area") if large else F.col("_area")).alias("_key"))
    places = ranked(keys, "_key", "object_id", below=min(upto, most * step)).where((F.col("rank") < min(upto, most * step)) & (F.col("rank") % step == 0))
    # The batch's ids come to the driver, so that objects are scanned for them and not shuffled.
    chosen = seeds.join(F.broadcast(seeds.sparkSession.createDataFrame(places.select("object_id").collect(), places.select("object_id").schema)), "object_id")
    dx, dy = F.floor((F.col("x1") - F.col("x0")) / 16), F.floor((F.col("y1") - F.col("y0")) / 16)
    sign = -1 if large else 1
    sides = [(F.col("x0") + sign * dx).alias("x0"), (F.col("y0") + sign * dy).alias("y0"), (F.col("x1") - sign * dx).alias("x1"), (F.col("y1") - sign * dy).alias("y1")]
    rows = chosen.select(F.col("object_id").alias("query_id"), *sides, "tokens")
    if large:
        heavy = rows.select("query_id", F.explode("tokens").alias("token")).join(ix.stats, "token")
        best = heavy.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("w"), "token"))).where(F.col("r") <= WORDS)
        rows = rows.drop("tokens").join(best.groupBy("query_id").agg(F.collect_list("token").alias("tokens")), "query_id", "left")
    tokens = F.coalesce(F.sort_array("tokens"), F.array().cast("array<string>"))
    return P.known_size(rows.select("query_id", *[F.col(s).cast("bigint").alias(s) for s in SIDES], tokens.alias("tokens"), F.lit(tau_r_bp).cast("bigint").alias("tau_r_bp"), F.lit(tau_t_bp).cast("bigint").alias("tau_t_bp")))


def with_thresholds(q: DataFrame, tau_r_bp: int, tau_t_bp: int) -> DataFrame:
    return q.withColumn("tau_r_bp", F.lit(tau_r_bp).cast("bigint")).withColumn("tau_t_bp", F.lit(tau_t_bp).cast("bigint"))


def of_objects(objects: DataFrame, tau_r_bp: int, tau_t_bp: int) -> DataFrame:
    """Every object as a query; stays distributed."""
    return with_thresholds(objects.select(F.col("object_id").alias("query_id"), *SIDES, "tokens"), tau_r_bp, tau_t_bp)
