"""Object sets: derivations from the given tables, files, and the worked example.

An object set is a DataFrame object_id, x0, y0, x1, y1 (BIGINT, upper sides open) and tokens (ARRAY<STRING>, distinct).
"""

from __future__ import annotations

import heapq
from collections import Counter
from collections.abc import Iterator
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from arealex.functions.similarity import SIDES
from arealex.sources.shared import kept

SCHEMA = "object_id bigint, x0 bigint, y0 bigint, x1 bigint, y1 bigint, tokens array<string>"
COLUMNS = ("object_id", *SIDES, "tokens")
#: Up to so many different words are bits of numbers while shipments are made; parts that are sent to all tasks then.
BIT_WORDS, BROADCAST_PARTS = 504, 2_000_000


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One object for each user and day: the bounding box of their events in (minute of month, cents), and the events' words."""
    rows = _events(spark, sf_dir)
    days = rows.agg(F.max(F.floor(F.col("x0") / 1440)), F.max("user_id")).first()
    return _gathered(rows.withColumn("object_id", F.col("user_id") * _room(100, days[0], days[1]) + F.floor(F.col("x0") / 1440)))


def first_users(spark: SparkSession, sf_dir: str, users: int = 7) -> DataFrame:
    """One object for each of the first users, of all their events."""
    return _gathered(_events(spark, sf_dir).where(F.col("user_id") < users).withColumn("object_id", F.col("user_id")))


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, sides and words of each event."""
    e = _table(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("bigint")
    minute = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.lit("2024-01-01 00:00:00").cast("timestamp"))) / 60_000_000)
    rows = e.select("user_id", "event_type", minute.cast("bigint").alias("m"), F.round(F.col("value") * 100).cast("bigint").alias("v"), k.alias("k"))
    words = F.array(F.col("event_type"), F.concat(F.lit("k"), F.floor(F.col("k") / 5).cast("string")), F.concat("event_type", F.lit(":"), F.floor(F.col("k") / 20).cast("string")))
    return rows.select("user_id", F.col("m").alias("x0"), F.col("v").alias("y0"), (F.col("m") + 1).alias("x1"), (F.col("v") + 1).alias("y1"), words.alias("words"))


def shipment(spark: SparkSession, sf_dir: str, apart: bool = False) -> DataFrame:
    """One object for each order and part: a rectangle around (ship day, price), with words of part, order and customer.

    As in the SQL, an object is what has the same order key * 1,000,000 + part key, so part keys from a million on can put two orders' parts into one object. With ``apart`` the factor is above all part keys, and no two fall together.
    """
    line, part, orders, customer = (_table(spark, sf_dir, t) for t in ("lineitem", "part", "orders", "customer"))
    keys = part.agg(F.min("p_partkey"), F.max("p_partkey"), F.count("*")).first()
    mult = _room(1_000_000, keys[1] if apart else 0, orders.agg(F.max("o_orderkey")).first()[0])
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("bigint")
    half = F.col("l_quantity").cast("bigint")
    price = F.round("l_extendedprice").cast("bigint")
    high = (200 + 100 * F.round(100 * (F.col("l_discount") + F.col("l_tax"))).cast("bigint")).cast("bigint")
    sides = [(day - half).alias("x0"), (price - high).alias("y0"), (day + half).alias("x1"), (price + high).alias("y1")]
    tag = lambda name, c: F.concat(F.lit(name), F.col(c).cast("string"))
    of_part = F.concat(F.split("p_name", " "), F.array(F.col("p_brand"), F.col("p_type"), F.concat(F.lit("size"), F.floor(F.col("p_size") / 10).cast("string"))))
    of_order, of_customer, of_line = [F.col("o_orderpriority"), tag("st", "o_orderstatus")], [F.col("c_mktsegment"), tag("nation", "c_nationkey")], [tag("rf", "l_returnflag"), tag("ls", "l_linestatus")]
    said = [part.select(F.explode(of_part).alias("word"))] + [t.select(c.alias("word")) for t, own in ((orders, of_order), (customer, of_customer), (line, of_line)) for c in own]
    words = [r.word for r in reduce(DataFrame.unionByName, [w.where("word is not null").distinct() for w in said]).distinct().sort("word").limit(BIT_WORDS + 1).collect()]
    if len(words) > BIT_WORDS:
        j = line.join(part, line.l_partkey == part.p_partkey).join(orders, line.l_orderkey == orders.o_orderkey).join(customer, orders.o_custkey == customer.c_custkey)
        return _gathered(j.select((F.col("l_orderkey") * mult + F.col("l_partkey")).alias("object_id"), *sides, F.concat(of_part, F.array(*of_order, *of_customer, *of_line)).alias("words")))
    # Words are bits of a few numbers until objects are whole, so that what is shuffled has no strings.
    bits = [f"_b{k}" for k in range(-(-len(words) // 63))]
    at = spark.createDataFrame([(w, *[1 << n % 63 if n // 63 == k else 0 for k in range(len(bits))]) for n, w in enumerate(words)], "_word string" + "".join(f", {b} bigint" for b in bits))

    def coded(rows: DataFrame, own: list[Column]) -> DataFrame:
        """The rows with the bits of some columns' words."""
        made = rows.select("*", *[F.lit(0).cast("bigint").alias(b) for b in bits])
        for c in own:
            both = made.withColumn("_own", c).join(F.broadcast(at.withColumnsRenamed({b: f"{b}_" for b in bits})), F.col("_own") == F.col("_word"), "left")
            made = both.select(*rows.columns, *[F.col(b).bitwiseOR(F.coalesce(f"{b}_", F.lit(0).cast("bigint"))).alias(b) for b in bits])
        return made

    each = part.select("p_partkey", F.explode_outer(of_part).alias("_own")).join(F.broadcast(at), F.col("_own") == F.col("_word"), "left")
    # A line whose part has no name has no words.
    parts = each.groupBy("p_partkey").agg(*[F.coalesce(F.bit_or(b), F.lit(0).cast("bigint")).alias(f"p{b}") for b in bits], F.max(F.col("_own").isNotNull()).alias("_named"))
    parts = F.broadcast(parts) if keys[2] <= BROADCAST_PARTS else parts
    buyers = coded(customer.select("c_custkey", "c_mktsegment", "c_nationkey"), of_customer).select("c_custkey", *[F.col(b).alias(f"c{b}") for b in bits])
    bought = coded(orders.select("o_orderkey", "o_custkey", "o_orderpriority", "o_orderstatus"), of_order).select("o_orderkey", "o_custkey", *bits).join(buyers, F.col("o_custkey") == F.col("c_custkey"))
    bought = bought.select("o_orderkey", *[F.col(b).bitwiseOR(F.col(f"c{b}")).alias(f"o{b}") for b in bits])
    lines = coded(line.select("l_orderkey", "l_partkey", *sides, "l_returnflag", "l_linestatus"), of_line).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    lines = lines.select("l_orderkey", "l_partkey", *SIDES, "_named", *[F.col(b).bitwiseOR(F.col(f"p{b}")).alias(b) for b in bits]).join(bought.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    rows = lines.select("l_orderkey", "l_partkey", *SIDES, *[F.when(F.col("_named"), F.col(b).bitwiseOR(F.col(f"o{b}"))).otherwise(F.lit(0).cast("bigint")).alias(b) for b in bits])
    whole = [*[F.min(c).alias(c) for c in SIDES[:2]], *[F.max(c).alias(c) for c in SIDES[2:]], *[F.bit_or(b).alias(b) for b in bits]]
    # Rows of an order are together after the join; only part keys that can meet another order's are brought together again.
    found = rows.groupBy("l_orderkey", "l_partkey").agg(*whole).select((F.col("l_orderkey") * mult + F.col("l_partkey")).alias("object_id"), "l_partkey", *SIDES, *bits)
    if (keys[0] or 0) < 0:
        found = found.groupBy("object_id").agg(*whole)
    elif (keys[1] or 0) >= mult:
        meets = F.pmod("l_partkey", F.lit(mult)) <= keys[1] - mult
        again = found.where(meets).groupBy("object_id").agg(*whole)
        found = found.where(~meets).drop("l_partkey").unionByName(again)
    return found.select("object_id", *SIDES, *bits).mapInArrow(partial(_spelled, words), SCHEMA)


def _spelled(words: list[str], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bits back to words."""
    names = pa.array(words, pa.string())
    for b in batches:
        n = b.num_rows
        bits = [np.unpackbits(np.ascontiguousarray(b.column(k).to_numpy(zero_copy_only=False)).view(np.uint8).reshape(n, 8), axis=1, bitorder="little")[:, :63] for k in range(5, b.num_columns)]
        row, at = np.nonzero(np.concatenate(bits, axis=1)) if bits else (np.zeros(0, np.int64),) * 2
        ends = np.append(0, np.cumsum(np.bincount(row, minlength=n)))
        yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.ListArray.from_arrays(pa.array(ends, pa.int32()), names.take(pa.array(at)))], names=list(COLUMNS))


def document(spark: SparkSession, sf_dir: str, most_words: int = 14) -> DataFrame:
    """One object for each document: a rectangle from its source and id, and its most frequent words."""
    d = _table(spark, sf_dir, "documents").where(F.col("doc_id").isNotNull())
    s = F.coalesce(F.regexp_extract("source", r"(\d+)", 1).try_cast("bigint"), F.lit(0).cast("bigint"))
    h1, h2 = (F.col("doc_id") * 7919 + 104729) % 1000003, (F.col("doc_id") * 15485863 + 32452843) % 1000003
    x0, y0 = (s % 5) * 20000 + h1 % 6000, F.floor(s / 5) * 20000 + h2 % 6000
    boxes = d.select(F.col("doc_id").alias("object_id"), x0.alias("x0"), y0.alias("y0"), (x0 + 1500 + (31 * h1 + h2) % 9500).alias("x1"), (y0 + 1500 + (31 * h2 + h1) % 9500).alias("y1"))
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda t: t != "")
    # A text's words stay in its row; only rows that share their id are brought together.
    again = kept(d.groupBy("doc_id").count().where("count > 1").select("doc_id"))
    key = F.col("doc_id").alias("object_id")
    once = d.join(again, "doc_id", "left_anti").select(key, words.alias("words")).mapInArrow(partial(_frequent, most_words), "object_id bigint, tokens array<string>")
    counts = d.join(again, "doc_id", "left_semi").select(key, F.explode(words).alias("token")).groupBy("object_id", "token").count()
    best = counts.withColumn("r", F.row_number().over(Window.partitionBy("object_id").orderBy(F.desc("count"), "token"))).where(F.col("r") <= most_words)
    tokens = once.unionByName(best.groupBy("object_id").agg(F.collect_list("token").alias("tokens")))
    return boxes.dropDuplicates(["object_id"]).join(tokens, "object_id", "left").select("object_id", *SIDES, F.coalesce("tokens", F.array().cast("array<string>")).alias("tokens"))


def _frequent(most: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The most frequent words of each row, ties by word."""
    for b in batches:
        best = [[w for _, w in heapq.nsmallest(most, [(-n, w) for w, n in Counter(words or ()).items()])] for a in range(0, b.num_rows, 256) for words in b.column(1).slice(a, 256).to_pylist()]
        yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(best, pa.list_(pa.string()))], names=["object_id", "tokens"])


def _room(least: int, largest: int | None, first: int | None) -> int:
    """What the first part of a two-part key is multiplied with, so that no two keys fall together: a power of ten above the largest second part. A key beyond BIGINT is an error."""
    room = least
    while room <= (largest or 0):
        room *= 10
    if (first or 0) >= (1 << 63) // room:
        raise ValueError("keys of two parts don't fit into a BIGINT")
    return room


def _gathered(rows: DataFrame) -> DataFrame:
    """Rows with the same object_id as one object: the bounding box, and the union of their words, after one shuffle."""
    low, high = ("x0", "y0"), ("x1", "y1")
    out = rows.groupBy("object_id").agg(*[F.min(c).alias(c) for c in low], *[F.max(c).alias(c) for c in high], F.array_distinct(F.flatten(F.collect_set("words"))).alias("tokens"))
    return out.select("object_id", *SIDES, F.filter("tokens", lambda t: t.isNotNull()).alias("tokens"))


def worked_example(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    """Seven objects and one query on a space of 120 by 120."""
    # The seven objects and the query.
    rows = [
        (1, 0, 70, 60, 120, ["t1", "t2"]),
        (2, 15, 75, 85, 100, ["t1", "t2", "t3"]),
        (3, 92, 62, 118, 118, ["t2", "t3", "t4"]),
        (4, 5, 10, 34, 50, ["t2", "t3"]),
        (5, 80, 70, 110, 100, ["t1", "t2"]),
        (6, 31, 5, 58, 48, ["t4", "t5"]),
        (7, 55, 20, 110, 56, ["t5"]),
    ]
    query = [(1, 35, 50, 75, 110, ["t1", "t2", "t3"], 2500, 3000)]
    return spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(query, "query_id bigint, x0 bigint, y0 bigint, x1 bigint, y1 bigint, tokens array<string>, tau_r_bp bigint, tau_t_bp bigint")


SETS = {"activity": activity, "shipment": shipment, "document": document}


def validated(frame: DataFrame, key: str = "object_id") -> DataFrame:
    """The frame with the object columns cast to their types and sets made of its token lists; a missing column is an error, a row without key or sides goes."""
    missing = [c for c in (key, *SIDES, "tokens") if c not in frame.columns]
    if missing:
        raise ValueError(f"columns are missing: {missing}")
    more = [c for c in frame.columns if c in ("tau_r_bp", "tau_t_bp")]
    tokens = F.array_distinct(F.filter(F.coalesce(F.col("tokens"), F.array().cast("array<string>")), lambda t: t.isNotNull()))
    out = frame.select(F.col(key).cast("bigint").alias(key), *[F.col(s).cast("bigint").alias(s) for s in SIDES], tokens.alias("tokens"), *[F.col(c).cast("bigint").alias(c) for c in more])
    return out.dropna(subset=[key, *SIDES]).where("x0 <= x1 and y0 <= y1")


def from_file(spark: SparkSession, path: str, kind: str, separator: str = " ") -> DataFrame:
    """Objects from parquet, JSON lines (tokens as a list) or CSV with a header (tokens in one field, parted by ``separator``). The schema is given, never inferred."""
    if kind == "csv":
        raw = spark.read.schema(SCHEMA.replace("array<string>", "string")).option("header", True).csv(path)
        return validated(raw.withColumn("tokens", F.filter(F.split("tokens", separator), lambda t: t != "")))
    return validated(spark.read.schema(SCHEMA).format(kind).load(path))


def scaled(frame: DataFrame, decimals: int, key: str = "object_id") -> DataFrame:
    """Objects with DOUBLE sides on an integer lattice of that many decimals: lower sides are rounded down and upper sides up."""
    f = 10**decimals
    down, up = (lambda c: F.floor(F.col(c) * f).cast("bigint").alias(c)), (lambda c: F.ceil(F.col(c) * f).cast("bigint").alias(c))
    rest = [c for c in frame.columns if c not in (key, *SIDES)]
    return frame.select(key, down("x0"), down("y0"), up("x1"), up("y1"), *rest)


def boxes_by_cluster(points: DataFrame, user: str, x: str, y: str, cell: int) -> DataFrame:
    """Several rectangles a user: one around the points in each coarse cell of side ``cell``."""
    at = points.withColumn("cx", F.floor(F.col(x) / cell)).withColumn("cy", F.floor(F.col(y) / cell))
    return at.groupBy(user, "cx", "cy").agg(F.min(x).alias("x0"), F.min(y).alias("y0"), (F.max(x) + 1).alias("x1"), (F.max(y) + 1).alias("y1"))
