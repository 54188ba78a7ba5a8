"""Connected components of a large edge table: forests of tasks, then alternating star contractions."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.llm.common import forget, stored

#: So many edges at most (16 bytes each, checked) are finished in one task; beyond it, contractions go on distributed.
SMALL_EDGES = 1_000_000


def roots_of(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct ids in the edges, and for each the smallest id that can be reached from it."""
    ids, at = np.unique(np.concatenate((u, v)), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    parent = np.arange(len(ids))
    while True:
        pa_, pb = parent[a], parent[b]
        open_ = pa_ != pb
        if not open_.any():
            return ids, ids[parent]
        a, b, pa_, pb = a[open_], b[open_], pa_[open_], pb[open_]
        np.minimum.at(parent, np.maximum(pa_, pb), np.minimum(pa_, pb))
        while True:
            up = parent[parent]
            if (up == parent).all():
                break
            parent = up


def _forest(with_roots: bool):
    """A mapInArrow function: the edges of a task as stars (id, smallest id reached), in chunks, so that memory is bounded by the distinct ids."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        u = v = np.zeros(0, np.int64)
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        held = 0

        def folded() -> None:
            nonlocal u, v, parts, held
            ids, low = roots_of(np.concatenate([u, *(p[0] for p in parts)]), np.concatenate([v, *(p[1] for p in parts)]))
            u, v, parts, held = ids, low, [], 0

        for batch in batches:
            parts.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            held += batch.num_rows
            if held >= max(SMALL_EDGES, 2 * len(u)):
                folded()
        folded()
        keep = slice(None) if with_roots else u != v
        yield pa.RecordBatch.from_arrays([pa.array(u[keep]), pa.array(v[keep])], names=["id", "component"] if with_roots else ["u", "v"])

    return work


def connected(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(id, component) for each id in ``edges`` (u, v): component is the smallest id that can be reached.

    Every task turns its edges into a forest of stars first. Few edges left (``SMALL_EDGES``) are finished in one task. More go through rounds in which every node links its larger neighbours, then its smaller ones, to the smallest it knows; what is left in the end are stars. Sums and joins are by key with map-side combining, nothing is collected but a count and a checksum.
    """
    now = stored(edges.select("u", "v").mapInArrow(_forest(False), "u long, v long"))
    seen = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    if seen[0] <= SMALL_EDGES:
        return now.coalesce(1).mapInArrow(_forest(True), "id long, component long")
    for _ in range(most_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # Minima are written, as the planner splits a hub's rows only in joins straight on shuffled tables.
        low = stored(both.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low")))
        large = stored(both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("low").alias("v")).distinct())
        floor = stored(large.groupBy("u").agg(F.min("v").alias("low")))
        small = large.join(floor, "u").select(F.when(F.col("v") == F.col("low"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("low").alias("v"))
        new = stored(small.where("u <> v").distinct())
        for old in (now, low, large, floor):
            forget(old)
        now, before = new, seen
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if seen == before:
            break
    else:
        raise RuntimeError("components did not settle")
    roots = now.select("v").distinct().select(F.col("v").alias("id"), F.col("v").alias("component"))
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(roots)


def spanning(adjacent: np.ndarray) -> np.ndarray:
    """For a symmetric boolean matrix: the smallest index in the component of each row."""
    n = len(adjacent)
    label = np.arange(n)
    reach = adjacent | np.eye(n, dtype=bool)
    while True:
        new = np.where(reach, label[None, :], n).min(1)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def spanned(pairs: np.ndarray, linked: Callable[[int, int], bool]) -> np.ndarray:
    """Of the marked pairs, those that a test links; pairs that are connected already aren't tested, so the result has the components, not every link."""
    n = len(pairs)
    out, own = np.zeros((n, n), bool), list(range(n))

    def root(k: int) -> int:
        while own[k] != k:
            k = own[k] = own[own[k]]
        return k

    for a, b in np.argwhere(pairs).tolist():
        x, y = root(a), root(b)
        if x != y and linked(a, b):
            out[a, b] = out[b, a] = True
            own[max(x, y)] = min(x, y)
    return out
