"""Mixing sources to target weights by entropy balancing, with built-in functions only.

The balanced rates of documents are those nearest to one copy each, in relative entropy, under one token constraint a source and the limit of copies. Their dual is convex with one multiplier for each source, and a document's rate is its exponential tilt: exp(multiplier * size), at most the limit. The multipliers are found by Newton's steps whose gradient and curvature are sums over all documents (of a source and size at once, as these share a rate), added up by source on all tasks. A bracket guards each step, and sums are of whole millionths, so no order of adding changes the result.

Rates are rounded into whole copies: the whole part, and one more where a hash of the document falls under the fraction. What a source then lacks or has too much is settled by running sums in a fixed random order, over the documents that fit, as often as any does; first with copies next to the rate, then, if a source is still off by more than ``WIDE`` of its target, with any number of copies up to the limit. What is left then is shorter than any such change; it is made up, as far as that brings the source nearer, by the next longer document in exchange for others.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from arealex.llm.common import SPACES, forget, stored

#: Sources are broadcast only up to this many rows (about 100 bytes each); beyond it, joins shuffle.
BROADCAST_ROWS = 20_000
#: A source that misses this part of its target may leave the copies next to the rate.
WIDE = 0.002
#: Newton's passes at most; 12 are the most that were seen (sizes with a heavy tail, 1 to 199 % of a source).
PASSES = 60


def size_of(text: Column) -> Column:
    """Words in a text; null has none."""
    return F.coalesce(F.size(F.filter(F.split(text, SPACES), lambda x: x != "")), F.lit(0)).cast("long")


def targets(sources: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share_percent: int = 150, most: int = 2) -> DataFrame:
    """Adds ``target`` to (source, source_size): by code point of the source, null last, the weights repeat; they share ``share_percent`` of all sizes, and none gets above ``most`` times its size.

    Resharing an excess until none is above ends where each target is the smaller of its limit and one common level times its weight. With sources in order of limit per weight, the limited ones come first.
    """
    order = Window.orderBy(F.col("source").isNull(), "source")
    w = F.element_at(F.array(*[F.lit(x) for x in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int")).cast("double")
    t = sources.withColumn("weight", w).withColumn("cap", F.col("source_size") * float(most))
    by_cap = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), "source")
    upto = by_cap.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    after = by_cap.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    t = t.withColumn("all", F.sum("source_size").over(everything) * (share_percent / 100.0))
    # The level if this source and all later ones are free.
    t = t.withColumn("before", F.sum("cap").over(upto) - F.col("cap")).withColumn("open", F.sum("weight").over(after))
    t = t.withColumn("level", (F.col("all") - F.col("before")) / F.col("open"))
    fits = F.col("level") * F.col("weight") <= F.col("cap")
    t = t.withColumn("common", F.min(F.when(fits, F.struct(F.col("cap") / F.col("weight"), F.col("level").alias("level")))).over(everything)["level"])
    return t.select("source", "source_size", F.round(F.least(F.col("cap"), F.coalesce(F.col("common") * F.col("weight"), F.col("cap"))), 6).alias("target"))


def multipliers(sizes: DataFrame, sources: DataFrame, n_sources: int, most: int) -> DataFrame:
    """Adds ``mean`` (size of a document with words) and ``m`` to (source, source_size, target): a document of a source has the rate exp(m * size / mean), at most ``most``. ``sizes`` has (source, size, n) of the documents with words.

    A source whose target is all that can be had gets the multiplier at which all its documents reach the limit; one without words or target gets one so low that rates are 0.
    """
    stat = sizes.groupBy("source").agg((F.sum(F.col("n") * F.col("size")) / F.sum("n")).alias("mean"), F.min("size").alias("least"))
    t, whole = F.col("target"), F.col("source_size")
    top, bottom = F.log(F.lit(float(most))) * F.col("mean") / F.col("least") * (1 + 1e-9), -F.log(whole / t) * F.col("mean") / F.col("least")
    state = sources.join(stat.withColumnRenamed("source", "_s"), F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s")
    none, full = F.coalesce(t <= 0, F.lit(True)) | F.col("mean").isNull(), t >= whole * most - 0.5
    start = F.when(none, F.lit(-1e12)).when(full, top).otherwise(F.lit(0.0))
    state = state.select("source", "source_size", "target", F.coalesce("mean", F.lit(1.0)).alias("mean"), start.alias("m"), F.when(t > whole, F.lit(0.0)).otherwise(bottom).alias("low"), F.when(t > whole, top).otherwise(F.lit(0.0)).alias("high"), (none | full).alias("done"))
    state = stored(state)
    for _ in range(PASSES):
        open_ = state.where("not done")
        if open_.isEmpty():
            break
        now = _join(sizes, open_, n_sources, ["m", "mean"]).where("m is not null")
        tilt = F.exp(F.col("m") * F.col("size") / F.col("mean"))
        words = (F.col("n") * F.col("size")).cast("decimal(22,0)")
        slope = F.when(tilt < most, (words * F.round(tilt * F.col("size") / F.col("mean") * 1e6).cast("decimal(15,0)")).cast("decimal(38,0)"))
        sums = now.groupBy("source").agg(F.sum((words * millionths(tilt, most)).cast("decimal(38,0)")).alias("got"), F.sum(slope).alias("slope"))
        both = _join(state, sums, n_sources, ["got", "slope"])
        off, bend = F.col("got").cast("double") / 1e6 - t, F.col("slope").cast("double") / 1e6
        both = both.withColumn("off", off).withColumn("low", F.when(F.col("off") < 0, F.col("m")).otherwise(F.col("low"))).withColumn("high", F.when(F.col("off") > 0, F.col("m")).otherwise(F.col("high")))
        newton, between = F.col("m") - F.col("off") / bend, F.when(F.col("low") * F.col("high") > 0, F.signum("high") * F.sqrt(F.col("low") * F.col("high"))).otherwise((F.col("low") + F.col("high")) / 16)
        step = F.when((bend > 0) & (newton > F.col("low")) & (newton < F.col("high")), newton).otherwise(between)
        met = F.col("done") | (F.abs("off") <= F.greatest(F.lit(0.5), t * 1e-6))
        new = stored(both.select("source", "source_size", "target", "mean", F.when(met, F.col("m")).otherwise(step).alias("m"), "low", "high", met.alias("done")))
        forget(state)
        state = new
    return state.select("source", "source_size", "target", "mean", "m")


def millionths(tilt: Column, most: int) -> Column:
    """A rate in whole millionths."""
    return F.round(F.least(tilt, F.lit(float(most))) * 1e6).cast("decimal(15,0)")


def _join(left: DataFrame, sources: DataFrame, n_sources: int, names: list[str]) -> DataFrame:
    right = sources.select(F.col("source").alias("_s"), *names)
    right = F.broadcast(right) if n_sources <= BROADCAST_ROWS else right
    return left.join(right, F.col("source").eqNullSafe(F.col("_s")), "left").drop("_s")


def _upto(rows: DataFrame) -> DataFrame:
    """Adds ``upto``, the running sum of size in a source by the random place. No task gets a whole source: sums of 4096 ranges of the place, then within a range."""
    ranged = rows.withColumn("range", F.substring("place", 1, 3))
    sums = ranged.groupBy("source", "range").agg(F.sum("size").alias("range_size"))
    before = Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("before", F.coalesce(F.sum("range_size").over(before), F.lit(0))).select(F.col("source").alias("_s"), F.col("range").alias("_r"), "before")
    inside = Window.partitionBy("source", "range").orderBy("place", "doc_id", "size", "row")
    placed = ranged.withColumn("inside", F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return placed.join(sums, F.col("source").eqNullSafe(F.col("_s")) & (F.col("range") == F.col("_r"))).withColumn("upto", F.col("before") + F.col("inside")).drop("_s", "_r", "range", "before", "inside")


def _can(left: Column, most: int, wide: bool) -> Column:
    """Whether a document can have one copy more where words are missing, or one less where there are too many; copies stay the rate's whole part or one above, or ``wide``: from none to the limit."""
    more = (left > 0) & (F.lit(wide) | (F.col("copies") == F.col("whole"))) & (F.col("copies") < most)
    less = (left < 0) & (F.col("copies") > (F.lit(0) if wide else F.col("whole")))
    return F.coalesce((F.col("size") > 0) & (more | less), F.lit(False))


def _balanced(picked: DataFrame, n: int, most: int, wide: bool, only: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Running sums over the documents that fit what a source (of those in ``only``) lacks or has too much, until none fits; the result and (source, left) of all. Each round settles a document at least, so it ends."""
    while True:
        lack = F.round(F.first("target")).cast("long") - F.sum(F.col("copies") * F.col("size"))
        least = [F.min(F.when(_can(F.lit(x), most, wide), F.col("size"))).alias(c) for x, c in ((1, "least_free"), (-1, "least_taken"))]
        left = stored(picked.groupBy("source").agg(lack.alias("left"), *least, F.first("target").alias("target")))
        fitting = left.where("(left > 0 and least_free <= left) or (left < 0 and least_taken <= -left)")
        if only is not None:
            fitting = fitting.join(only.select(F.col("source").alias("_s")), F.col("source").eqNullSafe(F.col("_s")), "left_semi")
        if fitting.isEmpty():
            return picked, left.select("source", "left", "target")
        state = _join(picked, fitting, n, ["left"])
        fits = _can(F.col("left"), most, wide) & (F.col("size") <= F.abs("left"))
        step = F.when(F.col("upto") <= F.abs("left"), F.signum("left").cast("long")).otherwise(F.lit(0))
        moved = _upto(state.where(fits)).withColumn("copies", F.col("copies") + step)
        old, picked = picked, stored(state.where(~F.coalesce(fits, F.lit(False))).select(*picked.columns).unionByName(moved.select(*picked.columns)))
        forget(old)


def _exchanged(picked: DataFrame, left: DataFrame, n: int, most: int, wide: bool, only: DataFrame | None = None) -> DataFrame:
    """For sources that miss their target though nothing fits: the shortest document above the rest changes its copy, and what this is too much goes back by running sums. A source keeps the change if it is nearer then; ends when none is."""
    names = picked.columns
    open_ = left.where("left <> 0")
    if only is not None:
        open_ = open_.join(only.select(F.col("source").alias("_s")), F.col("source").eqNullSafe(F.col("_s")), "left_semi")
    open_ = stored(open_.select("source", "left"))
    while True:
        over = _can(F.col("left"), most, wide) & (F.col("size") > F.abs("left"))
        best = _join(picked, open_, n, ["left"]).where(over)
        best = best.groupBy("source").agg(F.min(F.struct("size", "place", "doc_id", "row", F.signum("left").cast("long").alias("step"))).alias("b"))
        best = stored(best.select("source", F.col("b.row").alias("row"), F.col("b.step").alias("step")))
        if best.isEmpty():
            return picked
        turned = picked.withColumn("was", F.col("copies")).join(F.broadcast(best.drop("source")) if n <= BROADCAST_ROWS else best.drop("source"), "row", "left")
        tried, after = _balanced(stored(turned.withColumn("copies", F.col("copies") + F.coalesce("step", F.lit(0))).select(*names, "was")), n, most, wide, best)
        both = _join(open_, after.withColumnRenamed("left", "new"), n, ["new"]).withColumn("nearer", F.abs("new") < F.abs("left"))
        both = stored(both.where("nearer").select("source", "nearer", F.col("new").alias("left")))
        if both.isEmpty():
            forget(tried)
            return picked
        old, picked = picked, stored(_join(tried, both, n, ["nearer"]).withColumn("copies", F.when(F.col("nearer"), F.col("copies")).otherwise(F.col("was"))).select(*names))
        forget(old), forget(tried)
        open_ = both.where("left <> 0").select("source", "left")


def mix(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share_percent: int = 150, most: int = 2) -> DataFrame:
    """doc_id, source, size, source_size, target, rate, copies and taken for each row of ``docs`` (doc_id, source, text).

    Null texts have size 0; null is a source like others. Repeated rows are decided one by one, and which of several equal rows gets a copy doesn't matter. An empty table gives an empty result. Other columns are ignored. Copies are whole documents, 0 to the limit of ``targets``.
    """
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), size_of(F.col("text")).alias("size"))
    d = stored(sized.withColumn("row", F.monotonically_increasing_id()).withColumn("place", F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary"))))
    sizes = stored(d.groupBy("source", "size").agg(F.count("*").alias("n")))
    s = stored(targets(sizes.groupBy("source").agg(F.sum(F.col("n") * F.col("size")).alias("source_size")), weights, share_percent, most))
    n = s.count()
    s = stored(multipliers(sizes.where("size > 0"), s, n, most))
    start = _join(d, s, n, ["source_size", "target", "mean", "m"])
    rate = millionths(F.exp(F.col("m") * F.col("size") / F.col("mean")), most)
    chance = F.conv(F.substring("place", 4, 8), 16, 10).cast("double") / (1 << 32)
    start = start.withColumn("rate", F.when(F.col("size") > 0, rate.cast("double") / 1e6).otherwise(F.lit(0.0))).withColumn("whole", F.floor("rate").cast("long"))
    start = start.withColumn("copies", F.col("whole") + F.when(chance < F.col("rate") - F.col("whole"), 1).otherwise(0)).drop("mean", "m")
    picked, left = _balanced(stored(start), n, most, False)
    picked = _exchanged(picked, left, n, most, False)
    missed = F.round(F.first("target")).cast("long") - F.sum(F.col("copies") * F.col("size"))
    off = stored(picked.groupBy("source").agg(missed.alias("left"), F.first("target").alias("target")).where(F.abs("left") > F.col("target") * WIDE).select("source", "left"))
    if not off.isEmpty():
        picked, left = _balanced(picked, n, most, True, off)
        picked = _exchanged(picked, left, n, most, True, off)
    return picked.select("doc_id", "source", "size", "source_size", "target", "rate", "copies").withColumn("taken", F.col("copies") * F.col("size"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with each row as often as the mix takes it, with the columns it had. Rows of size 0 stay out."""
    same = Window.partitionBy("doc_id", "source", "size").orderBy(F.lit(0))
    plan = mix(docs, **options).withColumn("turn", F.row_number().over(Window.partitionBy("doc_id", "source", "size").orderBy(F.desc("copies"))))
    plan = plan.select(F.col("doc_id").alias("_d"), F.col("source").alias("_s"), F.col("size").alias("_n"), F.col("turn").alias("_t"), "copies").where("copies > 0 and _n > 0")
    names = docs.columns
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), size_of(F.col("text")).alias("size"))
    rows = rows.withColumn("turn", F.row_number().over(same))
    on = F.col("doc_id").eqNullSafe(F.col("_d")) & F.col("source").eqNullSafe(F.col("_s")) & (F.col("size") == F.col("_n")) & (F.col("turn") == F.col("_t"))
    return rows.join(plan, on).select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select("row.*")
