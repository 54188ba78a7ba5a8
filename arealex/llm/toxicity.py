"""Toxicity: a linear classifier over character n-grams whose features are scaled by naive Bayes log-count ratios.

Each text is the set of its hashed 3-, 4- and 5-grams (lower case, runs of white space as one space). A feature's value is 1 times its log-count ratio between toxic and other labelled texts; logistic regression with L2 is fitted on that.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ORDERS = (3, 4, 5)
_MULTIPLIER = np.uint32(0x9E3779B1)


class GramSets:
    """Sets of hashed n-grams; ``bits`` gives the number of buckets. Not shared between threads."""

    def __init__(self, bits: int):
        self.bits, self._stamp = bits, np.zeros(1 << bits, np.int64)

    def __call__(self, text: str | None) -> np.ndarray:
        text = " " + " ".join((text or "").lower().split()) + " "
        c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        parts = []
        with np.errstate(over="ignore"):
            c = (c + np.uint32(1)) * _MULTIPLIER
            c ^= c >> np.uint32(15)
            h = c.copy()
            for n in range(2, max(ORDERS) + 1):
                if len(c) < n:
                    break
                h = (h[:-1] * np.uint32(0x01000193)) ^ c[n - 1 :]
                h *= np.uint32(0x85EBCA6B)
                if n in ORDERS:
                    parts.append(((h ^ (h >> np.uint32(13))) * _MULTIPLIER) >> np.uint32(32 - self.bits))
        if not parts:
            return np.zeros(0, np.int64)
        ids = np.concatenate(parts).astype(np.int64)
        # The last writer of a bucket is the one that counts: a set without sorting.
        order = np.arange(len(ids))
        self._stamp[ids] = order
        return ids[self._stamp[ids] == order]


@dataclass(frozen=True)
class Model:
    weights: np.ndarray
    bias: float
    bits: int

    def scores(self, texts: list[str | None]) -> np.ndarray:
        sets = GramSets(self.bits)
        z = np.array([self.weights[sets(t)].sum() + self.bias for t in texts], np.float64)
        return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def fit(texts: list[str | None], labels: list[int], bits: int = 18, **options) -> Model:
    """fit_sets on texts."""
    sets = GramSets(bits)
    return fit_sets([sets(t).astype(np.int32) for t in texts], labels, bits, **options)


def fit_sets(feats: list[np.ndarray], labels: list[int], bits: int = 18, alpha: float = 1.0, l2: float = 1e-3, passes: int = 80) -> Model:
    """Log-count ratios, then logistic regression by full-batch adaptive gradient steps; classes weigh alike. With one class only, the score is constant."""
    y = np.array(labels, np.float64)
    if not len(y) or y.min() == y.max():
        rate = float(y.mean()) if len(y) else 0.0
        return Model(np.zeros(1 << bits, np.float32), 8.0 if rate else -8.0, bits)
    size = 1 << bits
    counts = [np.full(size, alpha), np.full(size, alpha)]
    for f, label in zip(feats, labels, strict=True):
        counts[label][f] += 1
    n1, n0 = y.sum(), len(y) - y.sum()
    ratio = np.log(counts[1] / (n1 + 2 * alpha)) - np.log(counts[0] / (n0 + 2 * alpha))
    # Buckets that one training text alone has say nothing about others.
    ratio[counts[0] + counts[1] < 2 * alpha + 3] = 0
    live = np.abs(ratio) > 0.25
    feats = [f[live[f]] for f in feats]
    row = np.repeat(np.arange(len(feats), dtype=np.int32), [len(f) for f in feats])
    col = np.concatenate(feats)
    used, at = np.unique(col, return_inverse=True)
    at = at.astype(np.int32)
    value = ratio[col].astype(np.float32)
    weight = np.where(y == 1, 0.5 / n1, 0.5 / n0)
    w, b = np.zeros(len(used)), 0.0
    grad2, bias2 = np.zeros(len(used)), 0.0
    for _ in range(passes):
        z = np.bincount(row, value * w[at], minlength=len(y)) + b
        err = (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y) * weight
        g = np.bincount(at, value * err[row], minlength=len(used)) + l2 * w / len(used)
        grad2 += g * g
        w -= 0.1 * g / (np.sqrt(grad2) + 1e-8)
        gb = err.sum()
        bias2 += gb * gb
        b -= 0.3 * gb / (np.sqrt(bias2) + 1e-8)
    full = np.zeros(size, np.float32)
    full[used] = w * ratio[used]
    return Model(full, float(b), bits)


def packed(ids: np.ndarray, bits: int) -> bytes:
    """A set of buckets in at most 2**bits / 8 bytes and one: its ids, or a bitmap if that is shorter."""
    if 4 * len(ids) <= (1 << bits) // 8:
        return b"i" + np.sort(ids).astype("<i4").tobytes()
    marks = np.zeros(1 << bits, np.uint8)
    marks[ids] = 1
    return b"m" + np.packbits(marks).tobytes()


def unpacked(data: bytes) -> np.ndarray:
    body = np.frombuffer(data, np.uint8, offset=1)
    return body.view("<i4") if data[:1] == b"i" else np.flatnonzero(np.unpackbits(body)).astype(np.int32)


def labelled_sample(docs: DataFrame, labels: DataFrame, per_class: int, bits: int = 18) -> list[tuple[bytes, int]]:
    """The whole texts, as packed sets of n-grams, of at most ``per_class`` documents of each label, those with the smallest hash of the id: the same ones in every run. A document with two labels counts as the higher one. Sets are made by tasks, so the driver holds 2 * per_class sets of at most 2**bits / 8 bytes, however long the texts are."""
    marks = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen: list = []
    for label in (0, 1):
        rows = marks.where(F.col("toxic").cast("int") == label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class).select("doc_id")
        chosen += [(r[0], label) for r in rows.collect()]
    if not chosen:
        return []
    known = docs.sparkSession.createDataFrame(chosen, "doc_id long, label int")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams = GramSets(bits)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([packed(grams(t), bits) for t in batch.column(0).to_pylist()], pa.binary()), batch.column(1)], names=["grams", "label"])

    # The list of chosen ids has at most 2 * per_class rows.
    rows = docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").where(F.col("text").isNotNull()).select("doc_id", "text", "label").distinct()
    found = rows.select("text", "label").mapInArrow(sets, "grams binary, label int").collect()
    return sorted((bytes(g), int(y)) for g, y in found)


def score(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """score and predicted of every whole text; null counts as empty. One row per row of ``docs``; other columns are ignored."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            s = model.scores(batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s, pa.float64()), pa.array((s >= threshold).astype(np.int32), pa.int32())], names=["doc_id", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(work, "doc_id long, score double, predicted int")


def train(docs: DataFrame, labels: DataFrame, per_class: int = 2500, bits: int = 18, **options) -> Model:
    """A model from at most ``per_class`` labelled documents of either class (the documented bound of the fit)."""
    rows = labelled_sample(docs, labels, per_class, bits)
    return fit_sets([unpacked(g) for g, _ in rows], [y for _, y in rows], bits, **options)
