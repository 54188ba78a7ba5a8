"""Helpers that the operators share: shared-folder tables, token regexes, hashing."""

from __future__ import annotations

import atexit
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but the six ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"
SPACES = r"[\x20\x09-\x0D]+"

_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only in local mode."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if spark.sparkContext.master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    made = getattr(shared_dir, "made", None)
    if made is None:
        made = shared_dir.made = "file://" + tempfile.mkdtemp(prefix="arealex-")
    return made


def drop_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def _clean() -> None:
    for spark, path in _written:
        try:
            drop_path(spark, path)
        except Exception:  # noqa: BLE001  the session may have ended before the interpreter
            return


atexit.register(_clean)


def stored(df: DataFrame, keep: bool = True) -> DataFrame:
    """``df`` written to a Parquet table in the shared folder and read again: it cuts lineage, and a lost executor costs nothing that was computed before."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/arealex-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if keep:
        _written.append((spark, path))
    back = spark.read.schema(df.schema).parquet(path)
    back._stored_at = path
    return back


def forget(df: DataFrame) -> None:
    """Deletes the files behind a stored() table that no plan reads any more."""
    path = getattr(df, "_stored_at", None)
    if path:
        drop_path(df.sparkSession, path)
        _written[:] = [x for x in _written if x[1] != path]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once: a lambda variable isn't inlined by the optimiser."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply) on an array of uint64."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BASE = np.uint64(0x9E3779B97F4A7C15)
_powers: dict[str, np.ndarray] = {}


def _power_table(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, for n positions."""
    if "up" not in _powers or len(_powers["up"]) < n:
        size = max(n, 1 << 16)
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        with np.errstate(over="ignore"):
            for name, b in (("up", _BASE), ("down", inverse)):
                steps = np.full(size, b, np.uint64)
                steps[0] = 1
                _powers[name] = np.multiply.accumulate(steps)
    return _powers["up"], _powers["down"]


def prefix_sums(data: np.ndarray) -> np.ndarray:
    """Running sums from which spans_of gets the hash of any span of data."""
    up, _ = _power_table(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=total[1:])
    return total


def spans_of(total: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of spans of the data that ``total`` was summed over (polynomial in a fixed odd base, then mixed)."""
    _, down = _power_table(len(total))
    with np.errstate(over="ignore"):
        return mix64((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of data[start:end] for many spans at once."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    return spans_of(prefix_sums(data), starts, ends)


_SPACE_BYTES = np.zeros(256, bool)
_SPACE_BYTES[[9, 10, 11, 12, 13, 32]] = True


def word_spans(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words in an array of UTF-8 bytes."""
    gap = np.ones(len(data) + 2, bool)
    gap[1:-1] = _SPACE_BYTES[data]
    turns = np.flatnonzero(gap[1:] != gap[:-1])
    return turns[::2], turns[1::2]
