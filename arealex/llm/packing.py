"""Sequence packing by bounded-space online best fit.

Every partition keeps a fixed number of open windows. A piece goes into the window that it fills best; when none has room, the fullest is emitted and the piece starts a new one. Documents longer than a window are cut into whole windows, which are emitted at once, and a rest. What stays open at the end of the partitions is merged: the leftovers of groups of partitions are packed again in the same way, until one group is left.
"""

from __future__ import annotations

import json
import os
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from arealex.llm.common import stored

PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, padded_to long"
_NAMES = [x.split()[0] for x in PIECE.split(", ")]


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: printable Latin-1 bytes stand for themselves, the others for 256 upwards in order."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


def load_encoder(path: str):
    """A function from text to token ids for a byte-level BPE file of the tokenizers library.

    Its merges are run by tiktoken, several times faster than the library itself with the same ids (tests hold them against each other); this needs a vocabulary whose ids follow the order of its merges, else the library is used. The library also takes the texts that tiktoken's pattern engine refuses, such as runs of a million spaces.
    """
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    vocab, letters = spec["model"]["vocab"], byte_alphabet()
    special = {x["content"]: x["id"] for x in spec.get("added_tokens", ())}
    merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
    in_order = all(vocab.get(a + b, -1) == 256 + k for k, (a, b) in enumerate(merges))
    own: list = []

    def library(text: str) -> list[int]:
        if not own:
            from tokenizers import Tokenizer

            os.environ["TOKENIZERS_PARALLELISM"] = "false"
            own.append(Tokenizer.from_file(path))
        return own[0].encode(text, add_special_tokens=False).ids

    if not in_order or spec.get("normalizer") is not None:
        return library
    import tiktoken

    pattern = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""  # fixed value: how byte-level BPE splits text
    ranks = {bytes(letters[c] for c in token): k for token, k in vocab.items() if token not in special}
    enc = tiktoken.Encoding("bytes", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)

    def encode(text: str) -> list[int]:
        try:
            return enc.encode(text, allowed_special="all")
        except ValueError:  # the pattern engine's stack is limited
            return library(text)

    return encode


class OpenWindows:
    """At most ``most`` open windows of ``size`` tokens."""

    def __init__(self, size: int, most: int):
        self.size, self.most = size, most
        self.room: list[tuple[int, int]] = []  # (free tokens, window), sorted
        self.held: dict[int, list[tuple]] = {}
        self._next = 0

    def place(self, pieces: list[tuple], total: int) -> list[list[tuple]]:
        """Puts pieces of ``total`` tokens together into one window; returns the windows that are emitted for it."""
        if total == self.size:
            return [pieces]
        out = []
        k = bisect_left(self.room, (total, -1))
        if k < len(self.room):
            free, window = self.room.pop(k)
        else:
            if len(self.room) >= self.most:
                _, fullest = self.room.pop(0)
                out.append(self.held.pop(fullest))
            free, window = self.size, self._next
            self._next += 1
            self.held[window] = []
        self.held[window] += pieces
        if free == total:
            out.append(self.held.pop(window))
        else:
            insort(self.room, (free - total, window))
        return out

    def rest(self) -> list[list[tuple]]:
        found = [self.held[w] for _, w in self.room]
        self.room, self.held = [], {}
        return found


def padded_length(filled: int, size: int) -> int:
    """What a sequence is padded to: nothing at a power of two, else the window's size."""
    return filled if filled & (filled - 1) == 0 else size


class _Rows:
    """Collects the pieces of sequences as columns; ``open_flag`` marks leftovers."""

    def __init__(self, size: int, part: int):
        self.size, self.next, self.cols = size, part << 33, [[] for _ in range(9)]

    def add(self, window: list[tuple], is_open: bool) -> None:
        to, at = padded_length(sum(p[2] for p in window), self.size), 0
        for doc_id, start, length, crc, tokens in window:
            for c, v in zip(self.cols, (doc_id, start, length, crc, tokens, self.next, at, to, is_open), strict=True):
                c.append(v)
            at += length
        self.next += 1

    def batch(self) -> pa.RecordBatch:
        cols, self.cols = self.cols, [[] for _ in range(9)]
        return pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in cols[:8]), pa.array(cols[8], pa.bool_())], names=[*_NAMES, "is_open"])


def pack(docs: DataFrame, vocabulary: str | None = None, size: int = 2048, open_windows: int = 64, end_id: int = 1, fan_in: int = 64) -> DataFrame:
    """The pieces of all packed documents (doc_id, text).

    A null text counts as empty: its document is the end id alone. Repeated rows are packed each on its own. An empty table gives no piece. Other columns are ignored. Sequence ids are unique, not gapless. Text is tokenised once; leftovers are merged from their pieces' descriptions, ``fan_in`` partitions at a time.
    """
    path = vocabulary or default_vocabulary()

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode = load_encoder(path)
        rows, windows = _Rows(size, TaskContext.get().partitionId()), OpenWindows(size, open_windows)
        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.array([*encode(text or ""), end_id], "<u4")
                n = len(ids)
                for start in range(0, n, size):
                    part = ids[start : start + size]
                    for window in windows.place([(doc_id, start, len(part), zlib.crc32(part.tobytes()), n)], len(part)):
                        rows.add(window, False)
            yield rows.batch()
        for window in windows.rest():
            rows.add(window, True)
        yield rows.batch()

    def again(last: bool):
        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            rows, windows = None, OpenWindows(size, open_windows)
            held: tuple | None = None  # the leftover being read: its pieces follow each other
            for batch in batches:
                for values in zip(*(batch.column(k).to_pylist() for k in range(7)), strict=True):
                    rows = rows or _Rows(size, (1 << 28) + TaskContext.get().partitionId())
                    seq, piece = values[5], values[:5]
                    if held is None or held[0] != seq:
                        if held is not None:
                            for window in windows.place(held[1], sum(p[2] for p in held[1])):
                                rows.add(window, False)
                        held = (seq, [])
                    held[1].append(piece)
                if rows is not None:
                    yield rows.batch()
            if held is not None:
                for window in windows.place(held[1], sum(p[2] for p in held[1])):
                    rows.add(window, False)
                for window in windows.rest():
                    rows.add(window, not last)
                yield rows.batch()

        return work

    schema = PIECE + ", is_open boolean"
    done = stored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(first, schema))
    closed, left, level = done.where(~F.col("is_open")), done.where("is_open"), 0
    groups = left.select(F.max(F.shiftright("sequence_id", 33))).first()[0]
    while groups is not None:
        groups = groups // fan_in
        level += 1
        key = F.shiftright("sequence_id", 33)
        slot = F.floor(F.pmod(key, F.lit(1 << 28)) / fan_in)
        merged = left.withColumn("slot", slot).repartitionByRange(groups + 1, "slot").sortWithinPartitions("slot", F.hash("sequence_id"), "sequence_id", "offset").drop("slot")
        step = stored(merged.mapInArrow(again(groups == 0), schema))
        closed = closed.unionByName(step.where(~F.col("is_open")).withColumn("sequence_id", F.col("sequence_id") + F.lit(level << 58)))
        left = step.where("is_open")
        if groups == 0:
            break
    return closed.drop("is_open")


def padding(pieces: DataFrame, size: int = 2048) -> DataFrame:
    """One row: sequences, tokens, padding tokens and their share."""
    each = pieces.groupBy("sequence_id").agg(F.sum("length").alias("tokens"), F.max("padded_to").alias("to"))
    return each.agg(F.count("*").alias("sequences"), F.sum("tokens").alias("tokens"), F.sum(F.col("to") - F.col("tokens")).alias("padding")).withColumn("padding_share", F.col("padding") / (F.col("padding") + F.col("tokens")))
