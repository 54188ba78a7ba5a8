"""Language identification by nearest centroid.

A text is the normalised TF-IDF vector of its hashed character 1-, 2- and 3-grams. Every language has several centroids (spherical k-means over its training texts); the nearest by cosine gives the language. A text that is further from it than almost all training texts of that centroid were is rejected.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

UNKNOWN = "und"
_MULTIPLIER = np.uint32(0x9E3779B1)


def has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def gram_counts(text: str, size: int) -> np.ndarray:
    """Counts of the hashed 1-, 2- and 3-grams of a text's letters; all that isn't a letter counts as one space."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    ascii_other = (c < 65) | ((c > 90) & (c < 97)) | ((c > 122) & (c < 170))
    c = np.where(ascii_other, np.uint32(32), c)
    c = c[(c != 32) | (np.concatenate((c[:1], c[:-1])) != 32)]
    c = np.concatenate(([np.uint32(32)], c, [np.uint32(32)]))
    with np.errstate(over="ignore"):
        one = (c + np.uint32(1)) * _MULTIPLIER
        one ^= one >> np.uint32(15)
        two = (one[:-1] * np.uint32(0x01000193)) ^ one[1:]
        three = (two[:-1] * np.uint32(0x01000193)) ^ one[2:]
        ids = np.concatenate([((h * np.uint32(0x85EBCA6B)) >> np.uint32(7)) % np.uint32(size) for h in (one, two, three)])
    return np.bincount(ids, minlength=size).astype(np.float32)


def _unit(m: np.ndarray) -> np.ndarray:
    return m / np.maximum(np.linalg.norm(m, axis=-1, keepdims=True), 1e-9)


@dataclass(frozen=True)
class Centroids:
    idf: np.ndarray
    matrix: np.ndarray  # one unit row for each centroid
    langs: list[str]  # of each row
    floor: np.ndarray  # of each row: the cosine below which a text is rejected

    def vectors(self, texts: list[str]) -> np.ndarray:
        return _unit(np.log1p(np.stack([gram_counts(t, len(self.idf)) for t in texts])) * self.idf)

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, float, bool]]:
        """(language, score from 0 to 1, cosine, rejected) of each text; ``und`` with score 0 if there is no letter, or nothing was learned."""
        out: list[tuple[str, float, float, bool]] = [(UNKNOWN, 0.0, 0.0, True)] * len(texts)
        real = [k for k, t in enumerate(texts) if has_letter(t)]
        if not self.langs:
            return out
        names = sorted(set(self.langs))
        owner = np.array([names.index(x) for x in self.langs])
        for at in range(0, len(real), 256):
            part = real[at : at + 256]
            cos = self.vectors([texts[k] for k in part]) @ self.matrix.T
            best = np.stack([cos[:, owner == j].max(1) for j in range(len(names))], 1)
            share = np.exp((best - best.max(1, keepdims=True)) * 20)
            share /= share.sum(1, keepdims=True)
            near = cos.argmax(1)
            for row, k in enumerate(part):
                c = float(cos[row, near[row]])
                j = int(owner[near[row]])
                out[k] = (names[j], float(np.clip(share[row, j] * min(1.0, max(0.0, c) ** 0.25), 0, 1)), c, c < float(self.floor[near[row]]))
        return out


def packed(counts: np.ndarray) -> bytes:
    """The buckets that are not 0, and their counts."""
    at = np.flatnonzero(counts)
    return at.astype("<u4").tobytes() + counts[at].astype("<f4").tobytes()


def unpacked(data: bytes, size: int) -> np.ndarray:
    n, out = len(data) // 8, np.zeros(size, np.float32)
    out[np.frombuffer(data, "<u4", n)] = np.frombuffer(data, "<f4", n, 4 * n)
    return out


def fit(samples: dict[str, list[str]], per_language: int = 4, size: int = 8192, **options) -> Centroids:
    """fit_counts on texts."""
    counts = {k: [packed(gram_counts(t, size)) for t in v if has_letter(t)] for k, v in samples.items()}
    return fit_counts(counts, per_language, size, **options)


def fit_counts(samples: dict[str, list[bytes]], per_language: int = 4, size: int = 8192, reject: float = 0.005, rounds: int = 8) -> Centroids:
    """IDF over all sampled texts (packed counts), then ``per_language`` centroids for each language. A centroid's floor is the cosine that a share of ``reject`` of its own texts stays under, less a margin."""
    samples = {k: v for k, v in sorted(samples.items()) if v}
    if not samples:
        return Centroids(np.ones(size, np.float32), np.zeros((0, size), np.float32), [], np.zeros(0))
    held = np.zeros(size)
    n = sum(map(len, samples.values()))
    for v in samples.values():
        for t in v:
            held += unpacked(t, size) > 0
    idf = (np.log((1 + n) / (1 + held)) + 1).astype(np.float32)
    rows, langs, floor = [], [], []
    # One language's counts are unpacked at a time.
    for lang, v in samples.items():
        x = _unit(np.log1p(np.stack([unpacked(t, size) for t in v])) * idf)
        k = min(per_language, len(x))
        # Far-apart starts: each next one is the text least like those taken.
        starts = [int((x @ x.mean(0)).argmax())]
        while len(starts) < k:
            starts.append(int((x @ x[starts].T).max(1).argmin()))
        c = x[starts]
        for _ in range(rounds):
            near = (x @ c.T).argmax(1)
            c = _unit(np.stack([x[near == j].mean(0) if (near == j).any() else c[j] for j in range(k)]))
        sims = x @ c.T
        near = sims.argmax(1)
        for j in range(k):
            own = sims[near == j, j]
            rows.append(c[j])
            langs.append(lang)
            floor.append(max(0.0, float(np.quantile(own, reject)) - 0.05) if len(own) else 0.0)
    return Centroids(idf, np.stack(rows).astype(np.float32), langs, np.array(floor))


def sample(docs: DataFrame, per_language: int, size: int = 8192) -> dict[str, list[bytes]]:
    """The gram counts of at most ``per_language`` whole texts for each value of lang, made by tasks (at most 8 * size bytes each, however long the texts are): those with the smallest hash of the id, the same ones in every run. Rows without doc_id are not learned from; equal rows count once."""
    known = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    sizes = dict(known.groupBy("lang").count().collect())
    spark = docs.sparkSession
    flat: list[tuple[int, str]] = []
    # Hashes are even, so a share of them holds about that share of the ids; a language whose ids repeat gets a larger share until it has enough.
    share = {lang: 2.0 * (per_language + 20) / n for lang, n in sizes.items()}
    while share:
        limits = [(lang, min((1 << 63) - 1, int(x * 2.0**64) - (1 << 63))) for lang, x in share.items()]
        limit = spark.createDataFrame(limits, "lang string, most long")
        low = known.select("lang", "doc_id", F.xxhash64("doc_id").alias("hash")).join(F.broadcast(limit), "lang").where("hash <= most")
        found: dict[str, list[tuple[int, int]]] = {lang: [] for lang in share}
        for lang, doc_id, h in low.select("lang", "doc_id", "hash").distinct().collect():
            found[lang].append((h, doc_id))
        for lang, ids in found.items():
            if len(ids) >= per_language or share[lang] >= 1:
                flat += [(i, lang) for _, i in sorted(ids)[:per_language]]
                del share[lang]
            else:
                share[lang] *= 8
    if not flat:
        return {}
    wanted = spark.createDataFrame(flat, "doc_id long, want string")

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            grams = [packed(gram_counts(t, size)) if has_letter(t) else None for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(grams, pa.binary())], names=["lang", "doc_id", "grams"])

    # The list has at most per_language ids for each language.
    rows = known.join(F.broadcast(wanted), "doc_id").where(F.col("lang") == F.col("want")).select("lang", "doc_id", "text").distinct()
    texts: dict[str, list[bytes]] = {}
    for lang, _, grams in sorted((r[0], r[1], bytes(r[2])) for r in rows.mapInArrow(counted, "lang string, doc_id long, grams binary").where("grams is not null").collect()):
        texts.setdefault(lang, []).append(grams)
    return {k: v[:per_language] for k, v in texts.items()}


def train(docs: DataFrame, per_language_texts: int = 400, size: int = 8192, **options) -> Centroids:
    """Centroids from at most ``per_language_texts`` labelled texts a language (the documented bound of the fit)."""
    return fit_counts(sample(docs, per_language_texts, size), size=size, **options)


def identify(docs: DataFrame, model: Centroids) -> DataFrame:
    """Language of every whole text: doc_id, lang_pred, score, cosine, rejected. Null, empty and letterless texts are ``und`` with score 0. One row per row of ``docs``; other columns are ignored."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = model.predict(batch.column(1).to_pylist())
            lang, score, cos, rejected = zip(*rows, strict=True) if rows else ((), (), (), ())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(cos, pa.float64()), pa.array(rejected, pa.bool_())], names=["doc_id", "lang_pred", "score", "cosine", "rejected"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(work, "doc_id long, lang_pred string, score double, cosine double, rejected boolean")
