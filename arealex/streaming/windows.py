"""Objects and matches from a stream of events.

Windows over a user's events become objects when the watermark passes their end. Standing queries are the static side: each micro-batch of objects is probed against them under frozen weights.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from arealex.functions.similarity import SIDES
from arealex.operators import probes as P
from arealex.plans.search import search

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, schema) -> DataFrame:
    """Events from the Parquet files named events* in a folder, as they arrive."""
    return spark.readStream.schema(schema).option("pathGlobFilter", "events*").parquet(folder)


def windowed_objects(events: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = "2 hours", session_gap: str | None = None) -> DataFrame:
    """user_id, start (epoch seconds), sides and tokens of each user's window: tumbling, sliding with ``slide``, or a session with ``session_gap``. Events later than ``delay`` behind the watermark are dropped by it."""
    at = F.col("ts").cast("timestamp")
    k = F.get_json_object("props", "$.k").cast("bigint")
    rows = events.select("user_id", at.alias("ts"), F.floor(F.unix_micros(at) / 60_000_000).cast("bigint").alias("m"), F.round(F.col("value") * 100).cast("bigint").alias("v"), F.array(F.col("event_type"), F.concat(F.lit("k"), F.floor(k / 5).cast("string"))).alias("words"))
    rows = rows.withWatermark("ts", delay) if events.isStreaming else rows
    w = F.session_window("ts", session_gap) if session_gap else (F.window("ts", length, slide) if slide else F.window("ts", length))
    out = rows.groupBy("user_id", w.alias("w")).agg(F.min("m").alias("x0"), F.min("v").alias("y0"), (F.max("m") + 1).alias("x1"), (F.max("v") + 1).alias("y1"), F.array_distinct(F.flatten(F.collect_set("words"))).alias("tokens"))
    return out.select("user_id", F.unix_seconds("w.start").alias("start"), *SIDES, "tokens")


def standing_matches(objects: DataFrame, frozen: P.Index, queries: DataFrame, sink: str, checkpoint: str, method: str = "two_filter") -> StreamingQuery:
    """Starts a query that appends the answers of standing queries among each micro-batch's new objects to a Parquet folder, one alert for each query and object. ``frozen`` gives space and weights of the last batch build."""
    q = P.known_size(queries)

    def match(batch: DataFrame, number: int) -> None:
        rows = batch.select(F.xxhash64("user_id", "start").alias("object_id"), *SIDES, "tokens").dropDuplicates(["object_id"])
        ix = P.Index(rows, frozen.measure, space=frozen.space, stats=frozen.stats)
        ix._made["count"] = frozen.count()
        found = search(ix, q, method).withColumn("batch", F.lit(number))
        # The batch number is in the path, so a batch that is run again replaces what it wrote.
        found.drop("batch").write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return objects.writeStream.foreachBatch(match).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def alerts_once(matches: DataFrame, delay: str = "1 day") -> DataFrame:
    """Of a stream of matches (query_id, object_id, ts), the first for each pair within the delay."""
    return matches.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["query_id", "object_id"])
