"""Near-duplicates by an inverted join on MinHash signature coordinates, confirmed on full sets.

1. Each text becomes its set of hashed word shingles, a signature of ``COORDS`` MinHash coordinates, and a 128-bit key of the set. Equal sets are one class from here on.
2. A class is posted under the values of its first ``POSTED`` coordinates. Lists of one are dropped. Two classes that are similar enough agree in at least ``m`` posted coordinates (but for a chance of ``LOSS``), so of each class's lists the m - 1 longest can be skipped: in an order by list length that all share, any such pair meets in one of the others. Very frequent shingles only lengthen lists that are skipped.
3. In a list, collisions over the whole signature are counted, and pairs at or above the match threshold tie classes together. Only a spanning set of ties leaves a task. A list longer than a block is cut into pieces that all get its representatives; only what these leave apart is compared further, so no task gets a whole list and near copies cost a pass over them.
4. The texts of each tied cluster meet in the same way, where shared shingles are counted exactly; the components of the links that hold are the result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from arealex.llm.common import mix64, span_hashes, stored, word_spans
from arealex.llm.components import connected, spanning

COORDS, POSTED, BLOCK, LIST_BLOCK, REPRESENTATIVES, LOSS = 64, 20, 128, 512, 8, 1e-6

_rng = np.random.default_rng(20240229)
_FACTORS = _rng.integers(1, 1 << 63, COORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SHIFTS = _rng.integers(0, 1 << 63, COORDS, dtype=np.uint64)
_PLACES = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def least_matches(k: int, percent: int, loss: float = LOSS) -> int:
    """The most matches that a pair with that similarity has in k coordinates, but for a chance of ``loss``."""
    p, below, m = percent / 100, 0.0, 0
    while m < k:
        below += comb(k, m) * p**m * (1 - p) ** (k - m)
        if below > loss:
            break
        m += 1
    return max(1, m)


def shingles(text: str | None, words: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles: ``words`` words each, A-Z in lower case; the whole sequence if there are fewer; none without words."""
    data = np.frombuffer((text or "").encode("utf-8", "surrogatepass").lower(), np.uint8)
    starts, ends = word_spans(data)
    if not len(starts):
        return np.zeros(0, np.uint64)
    h = span_hashes(data, starts, ends)
    k = min(words, len(h))
    with np.errstate(over="ignore"):
        total = np.full(len(h) - k + 1, np.uint64(k), np.uint64)
        for j in range(k):
            total = total * np.uint64(0x9E3779B97F4A7C15) + h[j : len(h) - k + 1 + j] * _PLACES[j % 64]
        return np.unique(mix64(total))


def signature(s: np.ndarray) -> np.ndarray:
    """The minimum of each coordinate's permutation over a set of hashes."""
    out = np.full(COORDS, np.iinfo(np.uint64).max, np.uint64)
    with np.errstate(over="ignore"):
        for at in range(0, len(s), 4096):
            part = (s[at : at + 4096, None] * _FACTORS) ^ _SHIFTS
            out = np.minimum(out, part.min(0))
    return out


def sign(docs: DataFrame, words: int = 5) -> DataFrame:
    """doc_id, text_key (hash of the whole text), n_shingles, k1 and k2 (the set's key; null for an empty set), posts (values of the posted coordinates) and sig (16 bits of each coordinate)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        salt = np.arange(1, COORDS + 1, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)
        for batch in batches:
            n, k1, k2, posts, sigs = [], [], [], [], []
            for text in batch.column(1).to_pylist():
                s = shingles(text, words)
                n.append(len(s))
                if not len(s):
                    k1.append(None), k2.append(None), posts.append([]), sigs.append(None)
                    continue
                with np.errstate(over="ignore"):
                    k1.append(int(s.sum().view(np.int64)))
                    k2.append(int(mix64(s ^ np.uint64(0xA5A5A5A5A5A5A5A5)).sum().view(np.int64)))
                    value = mix64(signature(s) + salt)
                posts.append(value[:POSTED].view(np.int64))
                sigs.append((value >> np.uint64(48)).astype("<u2").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(n, pa.int64()), pa.array(k1, pa.int64()), pa.array(k2, pa.int64()), pa.array(posts, pa.list_(pa.int64())), pa.array(sigs, pa.binary())], names=["doc_id", "text_key", "n_shingles", "k1", "k2", "posts", "sig"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("text_key"))
    return rows.mapInArrow(work, "doc_id long, text_key long, n_shingles long, k1 long, k2 long, posts array<long>, sig binary")


def by_group(keys: list[str], work: Callable[[dict[str, np.ndarray | list]], Iterator[tuple[int, int]]], names: list[str]):
    """A mapInArrow function over partitions in which the rows of a group follow each other: ``work`` gets the columns of one group and yields edges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None

        def groups(t: pa.Table, last: bool):
            nonlocal held
            if not t.num_rows:
                held = None
                return
            cols = [t.column(k).to_numpy() for k in keys]
            turn = np.zeros(t.num_rows - 1, bool)
            for c in cols:
                turn |= c[1:] != c[:-1]
            cuts = [0, *(np.flatnonzero(turn) + 1), t.num_rows]
            held = None if last else t.slice(cuts[-2])
            own = [t.column(n).to_pylist() if pa.types.is_string(t.schema.field(n).type) or pa.types.is_binary(t.schema.field(n).type) else t.column(n).to_numpy() for n in names]
            for a, b in zip(cuts[:-1], cuts[1:] if last else cuts[1:-1], strict=False):
                if b - a > 1:
                    yield {n: c[a:b] for n, c in zip(names, own, strict=True)}

        def edges(t: pa.Table, last: bool) -> pa.RecordBatch:
            pairs = [e for g in groups(t, last) for e in work(g)]
            u, v = zip(*pairs, strict=True) if pairs else ((), ())
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])

        for batch in batches:
            t = pa.Table.from_batches([batch])
            yield edges(t if held is None else pa.concat_tables([held, t]).combine_chunks(), False)
        if held is not None:
            yield edges(held, True)

    return run


def _stars(ids: np.ndarray, adjacent: np.ndarray) -> Iterator[tuple[int, int]]:
    if adjacent.sum() == np.trace(adjacent):
        return
    label = spanning(adjacent)
    for k in np.flatnonzero(label != np.arange(len(label))):
        yield int(ids[k]), int(ids[label[k]])


def _cross(side: np.ndarray) -> np.ndarray:
    """Which pairs a piece is for: those across its two sides, or all if it has one."""
    return np.ones((len(side), len(side)), bool) if (side == side[0]).all() else side[:, None] != side[None, :]


def linked(rows: DataFrame, key: str, names: list[str], compare: Callable[[dict, np.ndarray], np.ndarray], block: int) -> DataFrame:
    """Edges (u, v) that span what ``compare`` links in the groups of ``key``; rows are (key, id, names). ``compare(columns, wanted)`` returns the links among the rows of a piece, of which only ``wanted`` pairs matter.

    A group of at most ``block`` rows is one piece. A longer one is cut into pieces of that size by a hash, and each piece also gets the group's few representatives, so rows that are near one of them are in one component after a pass that is linear in the group. Only rows outside the group's largest component are compared further: with all rows in it, and with each other. So no pair of different components is left out, and no copy of a row is made for pairs that are known to be linked.
    """
    rows = rows.select(key, "id", *names)
    # Written, as the planner splits a long group's rows only in a join straight on shuffled tables.
    sizes = stored(rows.groupBy(key).agg(F.count("*").alias("n")).where("n > 1").select(key, F.ceil(F.col("n") / block).cast("int").alias("blocks")))
    whole = rows.join(sizes, key)

    def found(pieces: DataFrame) -> DataFrame:
        cols = [key, "a", "b"]

        def work(g: dict) -> Iterator[tuple[int, int]]:
            wanted = _cross(g["side"])
            yield from _stars(g["id"], compare(g, wanted) & wanted)

        parted = pieces.select(*cols, "id", "side", *names).repartition(*cols).sortWithinPartitions(*cols)
        return parted.mapInArrow(by_group(cols, work, ["id", "side", *names]), "u long, v long")

    zero = F.lit(0)
    first = whole.select(key, "id", *names, F.pmod(F.xxhash64("id", F.lit(5)), F.col("blocks")).cast("int").alias("a"), zero.alias("b"), zero.alias("side"))
    if sizes.where("blocks > 1").isEmpty():
        return found(first)
    large = stored(whole.where("blocks > 1"))
    slot = F.pmod(F.xxhash64("id", F.lit(9)), F.lit(REPRESENTATIVES))
    chosen = large.groupBy(key, slot).agg(F.min(F.struct(F.xxhash64("id", F.lit(11)).alias("h"), "id"))["id"].alias("id")).select(key, "id")
    shown = large.join(stored(chosen), [key, "id"], "left_semi").select(key, "id", *names, F.explode(F.sequence(zero, F.col("blocks") - 1)).alias("a"), zero.alias("b"), zero.alias("side"))
    edges = stored(found(first.unionByName(shown)))
    owner = stored(large.select(key, "id").distinct().join(connected(edges), "id", "left").select(key, "id", F.coalesce("component", "id").alias("component")))
    most = owner.groupBy(key, "component").agg(F.count("*").alias("n")).groupBy(key).agg(F.max(F.struct("n", "component"))["component"].alias("main"), F.sum("n").alias("n"), F.max("n").alias("inside"))
    most = stored(most.where("inside < n").select(key, "main", F.ceil(F.col("inside") / block).cast("int").alias("inner"), F.ceil((F.col("n") - F.col("inside")) / block).cast("int").alias("outer")))
    if most.isEmpty():
        return edges
    placed = stored(owner.join(most, key).select(key, "id", (F.col("component") != F.col("main")).alias("out"), "inner", "outer"))
    left = large.join(placed, [key, "id"])
    mine = lambda n: F.pmod(F.xxhash64("id", F.lit(5)), F.col(n)).cast("int")
    upto = lambda n: F.explode(F.sequence(zero, F.col(n) - 1))
    outside = left.where("out").select(key, "id", *names, mine("outer").alias("a"), upto("inner").alias("b"), F.lit(1).alias("side"))
    inside = left.where("not out").select(key, "id", *names, upto("outer").alias("a"), mine("inner").alias("b"), zero.alias("side"))
    # Pairs of blocks of the rows outside, told apart from the pieces above by negative numbers.
    among = left.where("out").select(key, "id", *names, mine("outer").alias("side"), upto("outer").alias("other"))
    among = among.select(key, "id", *names, (-1 - F.least("side", "other")).alias("a"), (-1 - F.greatest("side", "other")).alias("b"), "side")
    return edges.unionByName(found(outside.unionByName(inside).unionByName(among)))


def tied(classes: DataFrame, percent: int) -> DataFrame:
    """Edges (u, v) that tie classes (id, posts, sig) with enough equal coordinates; a spanning set for each list."""
    m = least_matches(POSTED, percent)
    need = least_matches(COORDS, percent)
    posts = classes.select("id", F.explode("posts").alias("value"))
    lists = stored(posts.groupBy("value").agg(F.count("*").alias("n")).where("n > 1"))
    own = Window.partitionBy("id")
    ranked = posts.join(lists, "value").select("id", "value", F.row_number().over(own.orderBy("n", "value")).alias("rank"), F.count("*").over(own).alias("lists"))
    # The lists of one come first in the order, so of the others all but the m - 1 longest are used.
    used = ranked.where(F.col("rank") <= F.col("lists") - (m - 1)).select("id", "value")
    used = stored(used.join(classes.select("id", "sig"), "id"))

    def compare(g: dict, wanted: np.ndarray) -> np.ndarray:
        sig = np.frombuffer(b"".join(g["sig"]), "<u2").reshape(-1, COORDS)
        if len(sig) == 2:
            return np.full((2, 2), (sig[0] == sig[1]).sum() >= need)
        equal = np.zeros((len(sig), len(sig)), np.uint8)
        for k in range(COORDS):
            equal += sig[:, k, None] == sig[None, :, k]
        return equal >= need

    return linked(used, "value", ["sig"], compare, LIST_BLOCK)


def shared_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairwise intersections of sorted sets, by products of 0/1 matrices over ranges of the elements."""
    n = len(sets)
    if n == 2:
        k = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        return np.array([[len(sets[0]), k], [k, len(sets[1])]])
    row = np.repeat(np.arange(n), [len(s) for s in sets])
    _, col, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    # Elements of one set alone add to no pair.
    live = times[col] > 1
    row, col = row[live], col[live]
    out = np.zeros((n, n), np.float32)
    if len(col):
        _, col = np.unique(col, return_inverse=True)
        order = np.argsort(col, kind="stable")
        row, col = row[order], col[order]
        width = max(256, (1 << 21) // n)
        for at in range(0, int(col[-1]) + 1, width):
            a, b = np.searchsorted(col, (at, at + width))
            m = np.zeros((n, min(width, int(col[-1]) + 1 - at)), np.float32)
            m[row[a:b], col[a:b] - at] = 1
            out += m @ m.T
    return out.astype(np.int64)


def confirmed(members: DataFrame, percent: int, words: int) -> DataFrame:
    """Edges (u, v) between members (id, cluster, text) of a cluster whose full sets are similar; a spanning set for each task."""

    def compare(g: dict, wanted: np.ndarray) -> np.ndarray:
        sets = [shingles(t, words) for t in g["text"]]
        both = shared_counts(sets)
        n = np.array([len(s) for s in sets])
        return 100 * both >= percent * (n[:, None] + n[None, :] - both)

    return linked(members, "cluster", ["text"], compare, BLOCK)


def _labelled(docs: DataFrame, percent: int, words: int) -> DataFrame:
    """doc_id, text_key, n_shingles and component_id of each row. What is linked are classes of equal sets, by a hash of the set's key, so rows that share a doc_id don't share links."""
    signed = stored(sign(docs, words))
    at = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "text_key"))).alias("at")
    classes = signed.where("n_shingles > 0").groupBy("k1", "k2").agg(at, F.first("posts").alias("posts"), F.first("sig").alias("sig")).where("at is not null")
    classes = stored(classes.withColumn("id", F.xxhash64("k1", "k2")))
    clusters = stored(connected(tied(classes.select("id", "posts", "sig"), percent)))
    first = classes.select("id", "at").join(clusters, "id").select("id", F.col("component").alias("cluster"), F.col("at.doc_id").alias("_d"), F.col("at.text_key").alias("_k"))
    texts = docs.select(F.col("doc_id").cast("long").alias("_d"), F.xxhash64("text").alias("_k"), "text")
    members = texts.join(first, ["_d", "_k"]).select("id", "cluster", "text")
    joined = stored(connected(confirmed(stored(members), percent, words)))
    owner = stored(classes.select("k1", "k2", F.col("at.doc_id").alias("doc"), "id").join(joined, "id", "left").withColumn("root", F.coalesce("component", "id")).drop("component", "id"))
    least = owner.groupBy("root").agg(F.min("doc").alias("component_id"))
    owner = owner.join(least, "root").select(F.col("k1").alias("_a"), F.col("k2").alias("_b"), "component_id")
    out = signed.select("doc_id", "text_key", "n_shingles", "k1", "k2").join(owner, (F.col("k1") == F.col("_a")) & (F.col("k2") == F.col("_b")), "left")
    return out.select("doc_id", "text_key", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def near_duplicates(docs: DataFrame, percent: int = 80, words: int = 5) -> DataFrame:
    """doc_id, n_shingles, component_id (the smallest id that can be reached over links) and kept (doc_id is its component's), one row for each row of ``docs`` (doc_id, text).

    Null, empty and wordless texts have an empty set and no link. Repeated rows are one document: each row is kept or not as the others; rows with one doc_id and different texts are linked each on its own. A row without doc_id has null in kept, and a component only if its set is another document's. An empty table gives an empty result. Other columns are ignored. Sets are of 64-bit hashes.
    """
    return _labelled(docs, percent, words).drop("text_key").withColumn("kept", F.col("doc_id") == F.col("component_id"))


def without_near_duplicates(docs: DataFrame, percent: int = 80, words: int = 5) -> DataFrame:
    """``docs`` with the columns it had and one document of each group of near-duplicates: the one with the smallest id, and of its repeated rows the smallest one. Rows without doc_id stay."""
    names, same = docs.columns, ["_d", "_k"]
    own = (F.col("doc_id").cast("long").alias("_d"), F.xxhash64("text").alias("_k"))
    labelled = _labelled(docs, percent, words).where("doc_id <> component_id")
    gone = labelled.select(F.col("doc_id").alias("_d"), F.col("text_key").alias("_k")).distinct()
    left = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("_row"), *own).join(gone, same, "left_anti")
    # Ids are counted first, so only rows that repeat are shuffled whole.
    twice = docs.where("doc_id is not null").groupBy(*own).agg(F.count("*").alias("_n")).where("_n > 1").drop("_n")
    once = left.join(twice, same, "left_semi").groupBy(*same).agg(F.min("_row").alias("_row"))
    return left.join(twice, same, "left_anti").select("_row").unionByName(once.select("_row")).select("_row.*")
