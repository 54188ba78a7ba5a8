"""Line dedup by a segment-partition edit join.

Two lines within ``tau`` edits share at least one of the tau + 1 even segments of either, at nearly the same place. So each distinct line is posted under its own segments and probes, for each length down to its own less tau, the places where a segment of such a line can lie. Lines that meet under a key are compared by a sketch that edits can change in a few bits only (parities of hashed letter pairs); those that pass form small clusters, whose texts are then verified with a banded bit-parallel edit distance. The classes are the components of the verified pairs, and the first line of a class stays.

Keys of lines that a task sees more than once are combined before the shuffle. Long lists are split by equal parts of the sketch, and what is still long is cut into pieces that share representatives.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arealex.llm.common import WORD, let, mix64, prefix_sums, spans_of, stored
from arealex.llm.components import connected, spanned
from arealex.llm.neardup import _stars, linked

LONG_LIST, BLOCK, NEAR = 256, 128, 16


def segments(n: int, tau: int) -> list[tuple[int, int]]:
    """Start and length of the tau + 1 even segments of a line of n characters; the longer ones come last."""
    short, longer = divmod(n, tau + 1)
    sizes = [short] * (tau + 1 - longer) + [short + 1] * longer
    return [(sum(sizes[:k]), sizes[k]) for k in range(tau + 1)]


def probe_starts(n: int, m: int, k: int, start: int, size: int, tau: int) -> range:
    """Where, in a line of n characters, segment k (at ``start``) of one of m <= n characters has to be looked for: no more edits than k lie before it, or than tau - k after it, and the difference in length counts in both."""
    d = n - m
    low = max(0, start - k, start + d - (tau - k))
    high = min(n - size, start + k, start + d + (tau - k))
    return range(low, high + 1)


def line_keys(lengths: np.ndarray, chars: np.ndarray, begin: np.ndarray, tau: int) -> tuple[np.ndarray, np.ndarray]:
    """(key, line) of all segments posted and probed, for lines laid end to end in ``chars``."""
    keys, owner = [], []
    total = prefix_sums(chars)
    for d in range(tau + 1):
        m = lengths - d
        short, longer = np.divmod(m, tau + 1)
        for k in range(tau + 1):
            first_long = tau + 1 - longer
            size = short + (k >= first_long)
            start = k * short + np.maximum(0, k - first_long)
            low = np.maximum(np.maximum(0, start - k), start + d - (tau - k))
            high = np.minimum(np.minimum(lengths - size, start + k), start + d + (tau - k))
            for step in range(2 * tau + 1):
                at = low + step
                ok = np.flatnonzero((at <= high) & (m > tau))
                if not len(ok):
                    continue
                s = begin[ok] + at[ok]
                with np.errstate(over="ignore"):
                    label = mix64(m[ok].astype(np.uint64) * np.uint64(64) + np.uint64(k))
                    keys.append(mix64(spans_of(total, s, s + size[ok]) ^ label))
                owner.append(ok)
    if not keys:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(keys), np.concatenate(owner)


def sketches(lengths: np.ndarray, chars: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """64 parities of hashed letter pairs for each line; an edit changes at most 4 of them."""
    out = np.zeros(len(lengths), np.uint64)
    if len(chars) < 2:
        return out
    with np.errstate(over="ignore"):
        pair = mix64(chars[:-1].astype(np.uint64) * np.uint64(0x1FFFFF) + chars[1:].astype(np.uint64))
    bits = np.uint64(1) << (pair >> np.uint64(58))
    sums = np.concatenate(([np.uint64(0)], np.bitwise_xor.accumulate(bits)))
    some = lengths > 1
    # Pairs that start in a line but its last character.
    out[some] = sums[begin[some] + lengths[some] - 1] ^ sums[begin[some]]
    return out


def sketch_parts(tau: int) -> list[tuple[int, int]]:
    """First bit and width of 4 * tau + 1 disjoint parts that make up the 64 bits of a sketch: of any 4 * tau bits, one part has none."""
    parts = min(4 * tau + 1, 64)
    cuts = [64 * k // parts for k in range(parts + 1)]
    # More flips than there are bits leave nothing to split by: one empty part holds all.
    return [(0, 0)] if 4 * tau >= 64 else [(a, b - a) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def within(a: str, b: str, tau: int) -> bool:
    """Whether the edit distance is at most tau: shared ends are cut off, then a band of 2 * tau + 1 diagonals is kept as bits."""
    if a == b:
        return True
    if len(a) > len(b):
        a, b = b, a
    if len(b) - len(a) > tau:
        return False
    low, high = 0, len(a)
    while low < high and a[low] == b[low]:
        low += 1
    cut = 0
    while cut < high - low and a[-1 - cut] == b[-1 - cut]:
        cut += 1
    a, b = a[low : len(a) - cut], b[low : len(b) - cut]
    m, n = len(a), len(b)
    if m == 0:
        return n <= tau
    width = 2 * tau + 1
    full = (1 << width) - 1
    up, down = (full >> tau) << tau, 0  # vertical steps of +1 and -1; bit k is row j - tau + k of column j
    cost = min(m, tau)
    where: dict[str, int] = {}
    for k, c in enumerate(a):
        where[c] = where.get(c, 0) | 1 << k
    for j in range(1, n + 1):
        rows = where.get(b[j - 1], 0)
        same = (rows >> j - tau - 1 if j > tau else rows << tau + 1 - j) & full
        level = ((((same & up) + up) ^ up) | same | down) & full
        right, left = (down | ~(level | up)) & full, level & up
        if j + tau <= m:
            cost += not level >> (width - 1) & 1
            # The last row can still be reached by deletions only; the band's end gives a bound.
            if cost > tau + (m - j) + tau:
                return False
        else:
            k = m - j + tau
            cost += (right >> k & 1) - (left >> k & 1)
        level >>= 1
        up, down = (left | ~(level | right)) & full, level & right
    return cost <= tau


def _lines(docs: DataFrame) -> DataFrame:
    """doc_id, text_key (hash of the whole text), line_no (from 0), id (hash of the line) and line, of all lines."""
    exploded = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), F.posexplode(F.split("text", "\n")).alias("line_no", "line"))
    return exploded.select("doc_id", "text_key", "line_no", F.xxhash64("line").alias("id"), "line")


def _posts(lines: DataFrame, tau: int) -> DataFrame:
    """key, id, sketch of each line that a task sees, once. A key with more than LONG_LIST lines in one batch is marked: its rows get ``hot`` and one more row (id null) tells the list so."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            ids = batch.column(0).to_numpy()
            _, first = np.unique(ids, return_index=True)
            fresh = [k for k in np.sort(first) if int(ids[k]) not in seen]
            if len(seen) < 500_000:  # bounds memory; a line that is posted again costs rows, not results
                seen.update(int(ids[k]) for k in fresh)
            ids = ids[fresh]
            texts = batch.column(1).take(pa.array(fresh, pa.int64())).to_pylist()
            lengths = np.array([len(t) for t in texts], np.int64)
            chars = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
            begin = np.concatenate(([0], np.cumsum(lengths)))[:-1].astype(np.int64)
            keys, owner = line_keys(lengths, chars, begin, tau)
            sketch = sketches(lengths, chars, begin)[owner]
            keys, who = keys.view(np.int64), ids[owner]
            names, count = np.unique(keys, return_counts=True)
            long = names[count > LONG_LIST]
            hot = np.isin(keys, long) if len(long) else np.zeros(len(keys), bool)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.concatenate((keys, long))),
                    pa.array(np.concatenate((who, np.zeros(len(long), np.int64)))),
                    pa.array(np.concatenate((sketch.view(np.int64), np.zeros(len(long), np.int64)))),
                    pa.array(np.concatenate((np.where(hot, 1, 0), np.full(len(long), 2))).astype(np.int8)),
                ],
                names=["key", "id", "sketch", "hot"],
            )

    return lines.select("id", "line").mapInArrow(work, "key long, id long, sketch long, hot byte")


def _close(sketch: np.ndarray, tau: int) -> np.ndarray:
    return np.bitwise_count(sketch[:, None] ^ sketch[None, :]) <= 4 * tau


def _ties(posts: DataFrame, tau: int) -> DataFrame:
    """Edges (u, v) between lines that meet under a key and have close sketches."""

    def short(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Compares lists of up to LONG_LIST rows; passes on the rows of longer or marked ones. Rows: kind 0 with an edge, kind 1 with key, id, sketch."""
        rest: list[np.ndarray] = [np.zeros(0, np.int64)] * 4
        long_key: int | None = None  # the list that is being passed on

        def deal(cols: list[np.ndarray], last: bool) -> pa.RecordBatch:
            nonlocal rest, long_key
            key, who, sk, mark = cols[0], cols[1], cols[2].view(np.uint64), cols[3]
            cuts = np.concatenate(([0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)])) if len(key) else np.zeros(1, np.int64)
            size = np.diff(cuts)
            done = len(size) if last or not len(size) else len(size) - 1
            if done < len(size) and (size[-1] > LONG_LIST or long_key == int(key[-1])):
                done, long_key = len(size), int(key[-1])
            edges: list[tuple[int, int]] = []
            u = v = pk = pi = ps = np.zeros(0, np.int64)
            if done:
                long = size[:done] > LONG_LIST
                long |= np.logical_or.reduceat(mark[: cuts[done]] != 0, cuts[:done])
                if long_key is not None:
                    long |= key[cuts[:done]] == long_key
                spot = np.repeat(np.arange(done), size[:done])
                pass_on = np.flatnonzero(long[spot] & (mark[: len(spot)] != 2))
                pk, pi, ps = key[pass_on], who[pass_on], cols[2][pass_on]
                # Lists of up to NEAR rows are looked into further only if some pair of them is close.
                look = ~long & (size[:done] > NEAR)
                for step in range(1, min(NEAR, int(size[:done].max()))):
                    at = np.flatnonzero((spot[step:] == spot[:-step]) & ~long[spot[step:]])
                    at = at[(np.bitwise_count(sk[at] ^ sk[at + step]) <= 4 * tau) & (who[at] != who[at + step])]
                    if step == 1:
                        two = at[size[spot[at]] == 2]
                        u, v = who[two], who[two + 1]
                        at = at[size[spot[at]] > 2]
                    look[spot[at]] = True
                for k in np.flatnonzero(look):
                    edges += _stars(who[cuts[k] : cuts[k + 1]], _close(sk[cuts[k] : cuts[k + 1]], tau))
            if long_key is not None and (not len(key) or int(key[-1]) != long_key or last):
                long_key = None
            if edges:
                more = np.array(edges, np.int64)
                u, v = np.concatenate((u, more[:, 0])), np.concatenate((v, more[:, 1]))
            rest = [c[cuts[done] :] for c in cols]
            kind = np.concatenate((np.zeros(len(u), np.int8), np.ones(len(pk), np.int8)))
            return pa.RecordBatch.from_arrays([pa.array(kind), pa.array(np.concatenate((u, pk))), pa.array(np.concatenate((v, pi))), pa.array(np.concatenate((np.zeros(len(u), np.int64), ps)))], names=["kind", "a", "b", "c"])

        for batch in batches:
            new = [batch.column(k).to_numpy() for k in range(4)]
            yield deal([np.concatenate(x) for x in zip(rest, new, strict=True)], False)
        yield deal(rest, True)

    # Rows known to be of a long list are spread by line; they are only passed on.
    listed = posts.repartition(F.when(F.col("hot") == 1, F.col("id")).otherwise(F.col("key"))).sortWithinPartitions("key")
    found = stored(listed.mapInArrow(short, "kind byte, a long, b long, c long"))
    edges = found.where("kind = 0").select(F.col("a").alias("u"), F.col("b").alias("v"))
    long = found.where("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("id"), F.col("c").alias("sketch"))
    long = long.distinct()
    # Close sketches agree in at least one of the parts.
    cut = [F.struct(F.lit(k).alias("part"), F.shiftrightunsigned("sketch", start).bitwiseAND(F.lit((1 << size) - 1 if size < 64 else -1)).alias("bits")) for k, (start, size) in enumerate(sketch_parts(tau))]
    long = stored(long.select("id", "sketch", "key", F.explode(F.array(*cut)).alias("p")).select("id", "sketch", F.xxhash64("key", "p.part", "p.bits").alias("list")))
    more = linked(long, "list", ["sketch"], lambda g, wanted: _close(g["sketch"].view(np.uint64), tau), BLOCK)
    return edges.unionByName(more)


def _verified(members: DataFrame, tau: int) -> DataFrame:
    """Edges (u, v) between members (id, cluster, line) within tau edits; a spanning set for each task."""

    def compare(g: dict, wanted: np.ndarray) -> np.ndarray:
        texts = g["line"]
        lengths = np.array([len(t) for t in texts], np.int64)
        chars = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
        sk = sketches(lengths, chars, np.concatenate(([0], np.cumsum(lengths)))[:-1].astype(np.int64))
        near = _close(sk, tau) & (np.abs(lengths[:, None] - lengths[None, :]) <= tau) & wanted
        return spanned(np.triu(near, 1), lambda a, b: within(texts[a], texts[b], tau))

    return linked(members, "cluster", ["line"], compare, BLOCK)


def _classed(docs: DataFrame, tau: int, least_chars: int, shorter: bool) -> DataFrame:
    """Every line that counts, with its place (doc_id, text_key, line_no), the first place of its class and how many lines the class has."""
    every = _lines(docs)
    lines = every.where(F.length("line") >= least_chars)
    found = every.where((F.length("line") >= least_chars) | F.col("line").rlike(WORD)) if shorter else lines
    place = ["doc_id", "text_key", "line_no"]
    found = stored(found.select(*place, "id"))
    clusters = stored(connected(_ties(_posts(lines, tau), tau)).select("id", F.col("component").alias("cluster")))
    # A line's text comes from its first place, so a very common line is looked up once and not sent to one task.
    places = found.groupBy("id").agg(F.min(F.struct(*place)).alias("first")).join(clusters, "id")
    places = stored(places.select("id", "cluster", F.col("first.doc_id").alias("_d"), F.col("first.text_key").alias("_k"), F.col("first.line_no").alias("_n")))
    same = (lines["id"] == places["id"]) & lines["doc_id"].eqNullSafe(places["_d"]) & (lines["text_key"] == places["_k"]) & (lines["line_no"] == places["_n"])
    members = lines.join(places.hint("shuffle_hash"), same).select(places["id"], "cluster", "line")
    members = stored(members.groupBy("id", "cluster").agg(F.first("line").alias("line")))
    joined = connected(_verified(members, tau))
    each = found.groupBy("id").agg(F.count("*").alias("n"), F.min(F.struct(*place)).alias("first"))
    each = stored(each.join(joined, "id", "left").withColumn("class", F.coalesce("component", "id")).drop("component"))
    whole = each.groupBy("class").agg(F.sum("n").alias("class_lines"), F.min("first").alias("first"))
    owner = each.select("id", "class").join(whole, "class").select("id", "class_lines", "first")
    out = found.join(owner, "id").select(*place, "first", "class_lines")
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("text_key") == F.col("first.text_key")) & (F.col("line_no") == F.col("first.line_no")))


def classes(docs: DataFrame, tau: int = 2, least_chars: int = 20, shorter: bool = False) -> DataFrame:
    """One row for each line with at least ``least_chars`` characters, and with ``shorter`` for each other line that isn't blank, too: doc_id, line_no, class_doc_id and class_line_no (the first line of its class, by doc_id, then hash of the text, then place), class_lines (how many lines the class has) and kept (it is that first line).

    A class is what can be reached over pairs of lines within ``tau`` edits; equal lines are one. Lines under ``least_chars`` characters, for which so many edits are too many, are of one class only if equal. Null and empty texts have no line. Rows with the same doc_id and text are one document, so a line and its repetition are kept or not alike; rows with the same doc_id, or none, and different texts are told apart. A row without doc_id counts as coming first. An empty table gives an empty result. Other columns are ignored. Lines are told apart by a 64-bit hash.
    """
    return _classed(docs, tau, least_chars, shorter).select("doc_id", "line_no", F.col("first.doc_id").alias("class_doc_id"), F.col("first.line_no").alias("class_line_no"), "class_lines", "kept")


def without_repeats(docs: DataFrame, tau: int = 2, least_chars: int = 20, shorter: bool = False) -> DataFrame:
    """``docs`` with the columns it had and every line dropped from text that isn't kept; documents of which no line is left go, those that had no line stay as they are."""
    gone = _classed(docs, tau, least_chars, shorter).where(~F.col("kept")).groupBy("doc_id", "text_key").agg(F.collect_set("line_no").alias("_gone"))
    gone = gone.select(F.col("doc_id").alias("_d"), F.col("text_key").alias("_k"), "_gone")
    names = docs.columns
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("row"), F.col("doc_id").cast("long").alias("d"), F.xxhash64("text").alias("k"))
    rows = rows.join(gone, F.col("d").eqNullSafe(F.col("_d")) & (F.col("k") == F.col("_k")), "left")
    own = F.col("row")["text"]
    some = F.col("_gone").isNull() | (F.size("_gone") < F.size(F.split(own, "\n")))
    text = F.when(F.col("_gone").isNull(), own).otherwise(let(F.split(own, "\n"), _left_of))
    return rows.where(some).select(*[(text if c == "text" else F.col("row").getField(c)).alias(c) for c in names])


def _left_of(lines: Column) -> Column:
    """``lines`` without the places in _gone: what lies between one of them and the next, so each line is copied once."""
    gone = F.array_sort(F.concat(F.array(F.lit(-1)), F.col("_gone"), F.array(F.size(lines))))
    return let(gone, lambda g: F.array_join(F.flatten(F.transform(F.sequence(F.lit(1), F.size(g) - 1), lambda k: F.slice(lines, F.get(g, k - 1) + 2, F.get(g, k) - F.get(g, k - 1) - 1))), "\n"))
