"""Shared plumbing of the document operators: scratch tables, sizing, text hashing."""

from __future__ import annotations

import atexit
import shutil
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_MULT = 0x9E3779B97F4A7C15 | 1


def scratch_root(spark: SparkSession) -> str:
    """Folder that driver and executors share; the cluster names it in spark.checkpoint.dir.

    Without that setting a local master gets a folder under /tmp/checkpoints, which is
    deleted when the program ends, and any other master uses the warehouse folder.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        root = f"/tmp/checkpoints/{spark.sparkContext.applicationId}"
        atexit.register(shutil.rmtree, root, ignore_errors=True)
        return f"file://{root}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write to the shared folder and read back: cuts the lineage and survives lost executors."""
    path = scratch_path(df.sparkSession, label)
    df.write.mode("overwrite").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.scratch = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete the files of materialised tables that no plan to come reads."""
    for df in tables:
        spark = df.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(df.scratch)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


BROADCAST_BYTES = 32 << 20


def broadcast_if(df: DataFrame, row_bytes: int) -> DataFrame:
    """df, a materialised table, with a broadcast hint if its rows are known to fit BROADCAST_BYTES.

    Beyond, the engine shuffles both sides of the join.
    """
    return F.broadcast(df) if df.count() * row_bytes <= BROADCAST_BYTES else df


def text_bytes(df: DataFrame, column: str = "text") -> int:
    """Exact UTF-8 size of a text column; one narrow scan."""
    return int(df.agg(F.sum(F.octet_length(column)).alias("b")).first()["b"] or 0)


def parts_for(total: int, target: int, least: int = 8) -> int:
    return max(least, -(-total // target))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def chunks(texts: pa.Array, size: int, rows: int = 512) -> Iterator[slice]:
    """Slices of at most `rows` texts, cut once they hold `size` bytes."""
    held, start = 0, 0
    for i, n in enumerate(pc.binary_length(texts).to_pylist()):
        held += n or 0
        if held >= size or i + 1 - start >= rows:
            yield slice(start, i + 1)
            held, start = 0, i + 1
    if start < len(texts):
        yield slice(start, len(texts))


def mix64(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over the whole word (in place)."""
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xA0761D6478BD642F)
    h ^= h >> np.uint64(32)
    return h


_POWERS: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64; short tables are kept."""
    known = _POWERS.get(base)
    if known is None or len(known) < n:
        known = np.full(max(n, 1 << 19), base, dtype=np.uint64)
        known[0] = 1
        known = np.multiply.accumulate(known)
        if len(known) <= 1 << 21:
            _POWERS[base] = known
    return known[:n]


def distinct(values: np.ndarray) -> np.ndarray:
    """Sorted distinct values; several times as fast as numpy's hashed unique on wide integers."""
    own = np.sort(values)
    keep = np.ones(len(own), dtype=bool)
    keep[1:] = own[1:] != own[:-1]
    return own[keep]


def member(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are in `known`, which is sorted."""
    if not len(known):
        return np.zeros(len(values), dtype=bool)
    at = np.searchsorted(known, values)
    at[at == len(known)] = 0
    return known[at] == values


class SpanHasher:
    """Polynomial fingerprints of arbitrary byte spans of one buffer, from prefix sums."""

    def __init__(self, data: np.ndarray) -> None:
        n = len(data)
        inverse = pow(_MULT, -1, 1 << 64)
        scaled = data.astype(np.uint64)
        scaled += np.uint64(1)
        scaled *= powers(_MULT, n)
        self._prefix = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(scaled, out=self._prefix[1:])
        self._undo = powers(inverse, n + 1)

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        h = self._prefix[end] - self._prefix[start]
        h *= self._undo[start]
        h ^= (end - start).astype(np.uint64) << np.uint64(48)
        return mix64(h)
