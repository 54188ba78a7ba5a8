"""Document fingerprints by a randomised edit embedding.

A text is cut into chunks at words that a hash picks. In each chunk a walk that all texts share reads the characters: at a step it writes the one under its place and moves on or stays, as a random table says for step and character. Few edits then change few symbols of what is written, at the same steps, as walks that an edit parts soon meet again: edit distance becomes Hamming distance. A fingerprint samples bits of what was written: each of its slots takes one chunk, the one whose first characters have the smallest of a random function (so both versions of a text take the same one), and reads bits at steps that are fixed for the slot. The likeness of two fingerprints comes from their Hamming distance. Bands, of bits sampled again over the slots, find pairs, which an edit distance verifies.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.llm.common import mix64, stored
from arealex.llm.components import connected, spanned
from arealex.llm.linededup import within
from arealex.llm.neardup import BLOCK, linked

SLOTS, BITS, CHUNK, ANCHOR, HEAD, WINDOW = 64, 16, 256, 16, 12, 4
#: Bands of a fingerprint, and the slots and bits of each that it samples. Edits leave most chunks alone, so the bits of a slot agree together: two texts meet if they agree in all slots of a band. Of unrelated texts, bits agree by chance, 1e-9 for a band.
BANDS, BAND_SLOTS, WIDTH = 64, 2, 30

_rng = np.random.default_rng(611)
_MOVES = _rng.integers(0, 2, (2 * CHUNK + WINDOW, 256), dtype=np.int64)
_SHIFTS = _rng.integers(0, 1 << 63, SLOTS, dtype=np.uint64)
_PLACES = _rng.integers(0, 2 * CHUNK, (SLOTS, BITS))
_SAMPLED = np.stack([np.concatenate([k * BITS + _rng.permutation(BITS)[: WIDTH // BAND_SLOTS] for k in _rng.permutation(SLOTS)[:BAND_SLOTS]]) for _ in range(BANDS)])
_INDEX = np.uint64(24)  # low bits that number the chunks of a call


def _chunks(c: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, length and text number of chunks: they start at texts, at picked words, and after CHUNK characters without one."""
    start_word = np.zeros(len(c), bool)
    if len(c) > 4:
        gap = (c == 32) | (c == 10)
        at = np.flatnonzero(gap[:-1] & ~gap[1:]) + 1
        at = at[at < len(c) - 3]
        with np.errstate(over="ignore"):
            h = (c[at].astype(np.uint64) << np.uint64(42)) ^ (c[at + 1].astype(np.uint64) << np.uint64(21)) ^ c[at + 2].astype(np.uint64)
            start_word[at[mix64(h) % np.uint64(ANCHOR) == 0]] = True
    full = begin < end
    start_word[begin[full]] = True
    cuts = np.flatnonzero(start_word)
    owner = np.searchsorted(end, cuts, side="right")
    stop = np.minimum(np.append(cuts[1:], len(c)), end[owner])
    pieces = -(-(stop - cuts) // CHUNK)
    number = np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    start = np.repeat(cuts, pieces) + number * CHUNK
    return start, np.minimum(CHUNK, np.repeat(stop, pieces) - start), np.repeat(owner, pieces)


def _walks(c: np.ndarray, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """What the walks write: a row for each step, a column for each chunk. A walk has two steps a character, which is what it needs on average."""
    order = np.argsort(-length, kind="stable")
    start, length = start[order], length[order]
    with np.errstate(over="ignore"):
        symbol = np.append((mix64(c.astype(np.uint64) + np.uint64(1)) >> np.uint64(56)).astype(np.uint8), np.uint8(0))
    steps = 2 * length
    longest = int(length[0]) if len(length) else 0
    place = np.zeros(len(start), np.int64)
    wrote = np.zeros((2 * longest + WINDOW, len(start)), np.uint8)
    for j in range(2 * longest):
        live = int(np.searchsorted(-steps, -j, side="left"))  # chunks with more than j steps
        p, s = place[:live], start[:live]
        seen = np.where(p < length[:live], symbol[np.minimum(s + p, len(c))], 0).astype(np.uint8)
        wrote[j, :live] = seen
        place[:live] = p + _MOVES[j, seen]
    out = np.empty_like(wrote)
    out[:, order] = wrote
    return out


def _heads(c: np.ndarray, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """A hash of each chunk's first characters."""
    padded = np.append(c, np.zeros(HEAD, np.uint32)).astype(np.uint64)
    h = np.zeros(len(start), np.uint64)
    with np.errstate(over="ignore"):
        for k in range(HEAD):
            h = h * np.uint64(0x9E3779B97F4A7C15) + np.where(k < length, padded[start + k] + np.uint64(1), np.uint64(0))
    return mix64(h)


def fingerprints(texts: list[str]) -> np.ndarray:
    """SLOTS * BITS bits, as bytes, for each text; equal texts have equal ones. A text without a character has zeros."""
    out = np.zeros((len(texts), SLOTS * BITS // 8), np.uint8)
    at = 0
    while at < len(texts):
        upto, total = at, 0
        while upto < len(texts) and (upto == at or total + len(texts[upto]) <= 1_000_000):
            total += len(texts[upto])
            upto += 1
        part = texts[at:upto]
        c = np.frombuffer("".join(part).encode("utf-32-le", "surrogatepass"), np.uint32)
        sizes = np.array([len(t) for t in part], np.int64)
        end = np.cumsum(sizes)
        if len(c):
            start, length, owner = _chunks(c, end - sizes, end)
            first = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
            heads, number = _heads(c, start, length), np.arange(len(start), dtype=np.uint64)
            taken = np.empty((len(first), SLOTS), np.int64)
            for k in range(SLOTS):
                rank = (mix64(heads ^ _SHIFTS[k]) >> _INDEX << _INDEX) | number
                taken[:, k] = (np.minimum.reduceat(rank, first) & np.uint64((1 << 24) - 1)).astype(np.int64)
            # Steps are read within the largest power of two that the walk has, so that a few characters more or less don't move them.
            room = 1 << np.floor(np.log2(2 * length)).astype(np.int64)
            steps = _PLACES[None] % room[taken][:, :, None]
            wrote, h = _walks(c, start, length), np.zeros(steps.shape, np.uint32)
            with np.errstate(over="ignore"):
                for k in range(WINDOW):
                    h = h * np.uint32(0x01000193) + wrote[steps + k, taken[:, :, None]] + np.uint32(1)
                h = (h ^ (h >> np.uint32(15))) * np.uint32(0x85EBCA6B)
            bits = (h >> np.uint32(31)).astype(np.uint8).reshape(len(first), -1)
            out[at + owner[first]] = np.packbits(bits, axis=1)
        at = upto
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """From 0 to 1: the share of what two texts have in common (twice the common part by all), from the Hamming distance of their fingerprints; bits of different texts agree in half of all cases."""
    apart = np.bitwise_count(a ^ b).sum(-1) / (SLOTS * BITS)
    j = np.clip(1 - 2 * apart, 0, 1)
    return 2 * j / (1 + j)


def bands(prints: np.ndarray) -> np.ndarray:
    """A 64-bit value for each band of each fingerprint: its number and its sampled bits."""
    bits = np.unpackbits(prints, axis=1)[:, _SAMPLED].astype(np.uint64)
    values = (bits << np.arange(WIDTH, dtype=np.uint64)).sum(-1, dtype=np.uint64)
    with np.errstate(over="ignore"):
        return mix64(values + (np.arange(BANDS, dtype=np.uint64) << np.uint64(40))).view(np.int64)


def near_copies(a: str, b: str, max_edits_percent: int) -> bool:
    """Whether so many edits for each hundred characters of the longer text make one of the other; bands of the edit distance are widened step by step, so few edits are found soon."""
    most, tau = max(len(a), len(b)) * max_edits_percent // 100, 8
    while tau < most:
        if within(a, b, tau):
            return True
        tau *= 4
    return within(a, b, most)


def edited(text: str, following: str) -> str:
    """The last third of the characters replaced by as many (or all) of the following text's first ones."""
    k = len(text) // 3
    return text[: len(text) - k] + following[:k]


_OUT = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "meets_edited", "meets_next", "copy_next"]
SCHEMA = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, meets_edited boolean, meets_next boolean, copy_next boolean"
#: What counts as a near copy: edits for each hundred characters of the longer text.
COPY_PERCENT = 3


def _compared(ids: list, texts: list[str], prints: np.ndarray, nexts: list[str], next_prints: np.ndarray) -> pa.RecordBatch:
    changed = [edited(t, n) for t, n in zip(texts, nexts, strict=True)]
    ep = fingerprints(changed)
    own = bands(prints)
    meets, meets_edited = (own == bands(next_prints)).any(1), (own == bands(ep)).any(1)
    copy = [bool(m) and near_copies(t, n, COPY_PERCENT) for m, t, n in zip(meets, texts, nexts, strict=True)]
    cols = [
        pa.array(ids, pa.int64()),
        pa.array([len(t) for t in texts], pa.int64()),
        pa.array([hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in changed], pa.string()),
        pa.array([p.tobytes().hex() for p in prints], pa.string()),
        pa.array([p.tobytes().hex() for p in ep], pa.string()),
        pa.array(likeness(prints, ep), pa.float64()),
        pa.array(likeness(prints, next_prints), pa.float64()),
        pa.array(meets_edited, pa.bool_()),
        pa.array(meets, pa.bool_()),
        pa.array(copy, pa.bool_()),
    ]
    return pa.RecordBatch.from_arrays(cols, names=_OUT)


def compare_neighbours(docs: DataFrame) -> DataFrame:
    """The fingerprints of each whole text and of its edited text, for the next document in descending order of doc_id (after the last: the first): likeness to the edited text's and the next one's, whether they share a band, and for a next one that does, whether the edit distance confirms a near copy (``COPY_PERCENT``).

    Null texts count as empty. Rows with the same doc_id follow each other by a hash of the text, rows without one come last. A single row is its own neighbour. An empty table gives an empty result. Other columns are ignored. Texts are dealt out by ranges of doc_id and sorted there; only a range's first and last text meet those of other ranges, in a second step over two rows a range.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # Rows that share an id are dealt out by their texts, equal ones by where they were read.
    order = (F.col("doc_id").desc_nulls_last(), F.col("h"), F.col("at"))
    ordered = rows.withColumn("h", F.xxhash64("text")).withColumn("at", F.monotonically_increasing_id()).repartitionByRange(parts, *order).sortWithinPartitions(*order).select("doc_id", "text")
    extra = ", part int, first_text string, last_text string"

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        held: tuple | None = None  # the last row so far: id, text, fingerprint
        first: str | None = None

        def plain(b: pa.RecordBatch) -> pa.RecordBatch:
            n = b.num_rows
            return pa.RecordBatch.from_arrays([*b.columns, pa.nulls(n, pa.int32()), pa.nulls(n, pa.string()), pa.nulls(n, pa.string())], names=[*_OUT, "part", "first_text", "last_text"])

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                ids, texts = (batch.column(k).slice(at, 512).to_pylist() for k in (0, 1))
                prints = fingerprints(texts)
                first = texts[0] if first is None else first
                if held is not None:
                    ids, texts, prints = [held[0], *ids], [held[1], *texts], np.concatenate((held[2][None], prints))
                held = (ids[-1], texts[-1], prints[-1])
                if len(ids) > 1:
                    yield plain(_compared(ids[:-1], texts[:-1], prints[:-1], texts[1:], prints[1:]))
        if held is not None:
            yield pa.RecordBatch.from_arrays(
                [pa.array([held[0]], pa.int64()), *(pa.nulls(1, t) for t in (pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64(), pa.bool_(), pa.bool_(), pa.bool_())), pa.array([part], pa.int32()), pa.array([first]), pa.array([held[1]])],
                names=[*_OUT, "part", "first_text", "last_text"],
            )

    done = stored(ordered.mapInArrow(walk, SCHEMA + extra))
    # One row for each range that has rows: it needs the first text of the next such range.
    ends = done.where(F.col("part").isNotNull()).select("part", "doc_id", "first_text", "last_text")

    def stitch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts, nexts = (batch.column(k).to_pylist() for k in range(3))
            if ids:
                yield _compared(ids, texts, fingerprints(texts), nexts, fingerprints(nexts))

    here = [r[0] for r in ends.select("part").orderBy("part").collect()]  # numbers of ranges, no rows of the table
    turn = spark.createDataFrame([(p, here[(k + 1) % len(here)]) for k, p in enumerate(here)], "part int, next_part int")
    pairs = ends.join(turn, "part").join(ends.select(F.col("part").alias("next_part"), F.col("first_text").alias("next_text")), "next_part")
    tail = pairs.select("doc_id", "last_text", "next_text").mapInArrow(stitch, SCHEMA)
    return done.where(F.col("part").isNull()).select(*_OUT).unionByName(tail)


def near_classes(docs: DataFrame, max_edits_percent: int = COPY_PERCENT, least_likeness: float = 0.4) -> DataFrame:
    """doc_id and component_id of texts linked by edit distance: at most ``max_edits_percent`` edits for each hundred characters of the longer one.

    Texts that share one of the bands of their fingerprints and have at least ``least_likeness`` meet, and an edit distance decides. Whether a pair meets is a matter of chance that falls with its edits (the README has measured figures); pairs in one class need not all meet. Equal texts are one class at once. Null texts count as empty; empty texts are one class. Rows that share a doc_id are linked each by its own text; a row without doc_id stays out of links. An empty table gives an empty result. Other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("text_key", F.xxhash64("text"))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = part.column(1).to_pylist()
                prints = fingerprints(texts)
                keys = [hashlib.blake2b(t.encode("utf-8", "surrogatepass"), digest_size=16).digest() for t in texts]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(keys, pa.binary()), pa.array([p.tobytes() for p in prints], pa.binary()), pa.array(list(bands(prints)), pa.list_(pa.int64()))], names=["doc_id", "text_key", "key", "print", "posts"])

    signed = stored(rows.mapInArrow(sign, "doc_id long, text_key long, key binary, print binary, posts array<long>"))
    at = F.min(F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "text_key"))).alias("at")
    one = stored(signed.groupBy("key").agg(at, F.first("print").alias("print"), F.first("posts").alias("posts")).where("at is not null").withColumn("id", F.xxhash64("key")))
    posts = one.select("id", F.explode("posts").alias("list"))
    shared = stored(posts.groupBy("list").agg(F.count("*").alias("n")).where("n > 1").drop("n"))
    used = stored(posts.join(shared, "list").join(one.select("id", "print"), "id"))

    def alike(g: dict, wanted: np.ndarray) -> np.ndarray:
        p = np.frombuffer(b"".join(g["print"]), np.uint8).reshape(len(g["print"]), -1)
        return np.stack([likeness(p, q) for q in p]) >= least_likeness

    clusters = stored(connected(linked(used, "list", ["print"], alike, BLOCK)).select("id", F.col("component").alias("cluster")))
    first = one.select("id", "at.*", "print").join(clusters, "id")
    members = stored(rows.join(first, ["doc_id", "text_key"]).select("id", "cluster", "print", "text"))

    def verify(g: dict, wanted: np.ndarray) -> np.ndarray:
        texts = g["text"]
        return spanned(np.triu(alike(g, wanted) & wanted, 1), lambda a, b: near_copies(texts[a], texts[b], max_edits_percent))

    joined = stored(connected(linked(members, "cluster", ["print", "text"], verify, BLOCK)))
    owner = stored(one.select("key", F.col("at.doc_id").alias("doc"), "id").join(joined, "id", "left").withColumn("root", F.coalesce("component", "id")).drop("component", "id"))
    owner = owner.join(owner.groupBy("root").agg(F.min("doc").alias("component_id")), "root").select("key", "component_id")
    return signed.select("doc_id", "key").join(owner, "key", "left").select("doc_id", F.coalesce("component_id", "doc_id").alias("component_id"))
