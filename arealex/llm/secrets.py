"""Secret scan: fixed detectors, and spans that look more like random strings than like identifiers under two character Markov models.

The two models are first-order chains over printable ASCII. The *random* one is trained on labelled random strings (hexadecimal, base 36, base 62, base 64), the *ordinary* one on words and identifiers of a bounded sample of texts. A token's score is its log-likelihood ratio for each transition.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

KINDS = ("assign", "access", "hex", "markov")

# The detectors of the base.
ASSIGN = re.compile(r"(?ai:(password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 6, 20, 24

#: What the Markov models look at.
TOKEN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
LONG_HEX = re.compile(r"[0-9a-f]{24,}")
ALPHABETS = {
    "hex": "0123456789abcdef",
    "base36": "0123456789abcdefghijklmnopqrstuvwxyz",
    "base62": "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz",
    "base64": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/",
}
_STATES = 96  # printable ASCII, and one state for the start


def _codes(token: str) -> np.ndarray:
    return np.clip(np.frombuffer(token.encode("ascii", "replace"), np.uint8).astype(np.int64) - 31, 0, _STATES - 1)


@dataclass(frozen=True)
class MarkovPair:
    """Log-likelihood ratios of transitions, and the mean a secret has to reach."""

    ratio: np.ndarray
    threshold: float

    def score(self, token: str) -> float:
        c = _codes(token)
        return float(self.ratio[c[:-1], c[1:]].mean()) if len(c) > 1 else 0.0


def train(random_strings: Iterable[str], ordinary: Iterable[str], threshold: float = 0.35, smoothing: float = 0.5) -> MarkovPair:
    """Both chains with additive smoothing; the ratio is the random chain's log-probability less the ordinary one's."""

    def chain(tokens: Iterable[str]) -> np.ndarray:
        counts = np.full((_STATES, _STATES), smoothing)
        for t in tokens:
            c = _codes(t)
            np.add.at(counts, (c[:-1], c[1:]), 1)
        return np.log(counts / counts.sum(1, keepdims=True))

    return MarkovPair((chain(random_strings) - chain(ordinary)).astype(np.float32), threshold)


def labelled_random(n: int = 4000, seed: int = 7) -> list[str]:
    """Labelled random strings: equal parts of each alphabet, 16 to 64 characters."""
    rng = np.random.default_rng(seed)
    return ["".join(rng.choice(list(a), rng.integers(16, 65))) for a in ALPHABETS.values() for _ in range(n // len(ALPHABETS))]


def without_spans(text: str, spans: list[tuple[int, int, int]], mask: str = " ") -> str:
    """The text with each stretch that sorted spans cover replaced by ``mask``."""
    cuts, at = [], 0
    for start, _, end in spans:
        if end > at:
            cuts += [text[at : max(at, start)], mask] if start >= at else []
            at = end
    return "".join(cuts) + text[at:]


def labelled_ordinary(texts: Iterable[str | None], most: int = 60_000) -> list[str]:
    """Words of the texts, without the spans of the fixed detectors, and identifiers made of them: joined by ``_``, ``-``, ``/`` or capitals, some with a number at the end."""
    words: list[str] = []
    for t in texts:
        words += re.findall(r"[A-Za-z]{2,}", without_spans(t or "", base_spans(t or "")))
        if len(words) > most:
            break
    words = words[:most] or ["value", "name", "item", "index"]
    out = list(words)
    for k in range(0, len(words) - 3, 3):
        a, b, c = words[k : k + 3]
        out += (a.upper() + b.upper(), f"{a}_{b}_{c}", a + b.capitalize() + c.capitalize(), f"{a}-{b}-{c}", f"{a}/{b}/{c}", f"{a}_{b}{k % 100}", f"{a}{b}{c}".lower())
    return out + ["2024-01-01", "2023_11_30", "1234567890", "0000000000", "=" * 30, "-" * 30, "_" * 30] * 20


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the fixed detectors; each kind's matches are leftmost and don't overlap."""
    out = []
    if ":" in text or "=" in text:
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LEAST]
    # A greedy match is a whole run, so runs that are long enough are the matches that stay.
    out += [(m.start(), 2, m.end()) for m in LONG_HEX.finditer(text)]
    return sorted(out)


def markov_spans(text: str, model: MarkovPair, taken: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(start, 3, end) of tokens that score as random strings and that no base span of ``taken`` (sorted) touches; both lists are walked once."""
    out, at, reached = [], 0, -1
    for m in TOKEN.finditer(text):
        while at < len(taken) and taken[at][0] < m.end():
            reached = max(reached, taken[at][2])
            at += 1
        if reached <= m.start() and model.score(m[0]) >= model.threshold:
            out.append((m.start(), 3, m.end()))
    return out


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, n_markov long, base_sha256 string, spans string"


def sample_texts(docs: DataFrame, rows: int) -> list[str]:
    """At most ``rows`` texts, of those whose hash falls into a share that gives about four times as many the ones with the smallest hash: the same ones in every run. So tasks send few texts, however many tasks there are."""
    share = F.lit(max(1, docs.count() // (4 * rows)))
    h = F.xxhash64("doc_id")
    found = docs.where(F.col("text").isNotNull() & (F.pmod(h, share) == 0)).select("doc_id", "text").orderBy(h, "text").limit(rows).select("text").collect()
    return [r[0] for r in found]


def scan(docs: DataFrame, sample_rows: int = 300, threshold: float = 0.35) -> DataFrame:
    """Spans of every whole text, one row per row of ``docs`` (doc_id, text).

    ``sample_rows`` bounds the texts that the ordinary model is trained on; random strings are generated. Null and empty texts have no span. Repeated rows give repeated rows. An empty table gives an empty result. Other columns are ignored.
    """
    model = train(labelled_random(), labelled_ordinary(sample_texts(docs, sample_rows)), threshold)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, rows = batch.column(0), []
            for text in batch.column(1).to_pylist():
                text = text or ""
                base = base_spans(text)
                more = markov_spans(text, model, base)
                n = [sum(k == j for _, k, _ in base) for j in range(3)]
                rows.append((*n, len(more), hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(sorted(base + more))))
            cols = list(zip(*rows, strict=True)) or [()] * 6
            yield pa.RecordBatch.from_arrays([ids, *(pa.array(c, pa.int64()) for c in cols[:4]), *(pa.array(c, pa.string()) for c in cols[4:])], names=["doc_id", "n_assign", "n_access", "n_hex", "n_markov", "base_sha256", "spans"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(work, SCHEMA)


def redact(docs: DataFrame, spans: DataFrame, mask: str = "[SECRET]") -> DataFrame:
    """``docs`` with the spans that scan() found replaced by ``mask``, spans that overlap by one: doc_id and text. One row of ``spans`` per doc_id is expected; a document without one stays as it is, null texts stay null. An empty table gives an empty result."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, found in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist(), strict=True):
                parts = (x.split(":") for x in (found or "").split(",") if x)
                texts.append(None if text is None else without_spans(text, sorted((int(a), 0, int(b)) for _, a, b in parts), mask))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    both = docs.select("doc_id", "text").join(spans.select("doc_id", "spans"), "doc_id", "left")
    return both.mapInArrow(work, docs.select("doc_id", "text").schema)
