"""Shared helpers: scratch tables in the cluster's shared folder, text buffers and rolling hashes."""

from __future__ import annotations

import ctypes
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_U = np.uint64
_LIVE: dict[str, list[str]] = {}


def scratch_path(spark: SparkSession, name: str, tracked: bool = True) -> str:
    """A new path below ``spark.checkpoint.dir``; where that is unset, a temporary folder in local mode and an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not re.match(r"local($|\[)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir is not set: name a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="prefgraph-")
        spark.conf.set("spark.checkpoint.dir", base)
    path = f"{base.rstrip('/')}/scratch-{name}-{uuid.uuid4().hex}"
    if tracked:
        live(spark).append(path)
    return path


def live(spark: SparkSession) -> list[str]:
    """The scratch paths of this application."""
    return _LIVE.setdefault(spark.sparkContext.applicationId, [])


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: cuts the lineage and survives lost executors."""
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    stored = df.sparkSession.read.schema(df.schema).parquet(path)
    stored.scratch = path
    return stored


def discard(stored: DataFrame) -> None:
    """Delete a table of materialize() that no unread result depends on."""
    delete_path(stored.sparkSession, stored.scratch)
    live(stored.sparkSession).remove(stored.scratch)


def delete_path(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_key(text: Column) -> list[Column]:
    """Two independent 64-bit hashes of a text, as columns t1 and t2; equal texts have equal keys."""
    whole = F.coalesce(text, F.lit(""))
    return [F.xxhash64(whole).alias("t1"), F.xxhash64(F.lit(0x5BD1E995), whole).alias("t2")]


def partitions_for(rows: int, per: int) -> int:
    return max(1, -(-rows // per))


# ---- text columns as flat byte buffers ------------------------------------------------------

def text_buffers(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, bounds) of a string column without copies per row; a null has no bytes."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) else np.int32
    if not len(column):
        return np.empty(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    bounds = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)
    return raw[bounds[0] : bounds[-1]], bounds - bounds[0]


def row_blocks(bounds: np.ndarray, limit: int):
    """Consecutive row ranges of about ``limit`` bytes; a longer row is a range of its own."""
    first, n = 0, len(bounds) - 1
    while first < n:
        last = int(np.searchsorted(bounds, bounds[first] + limit, side="right")) - 1
        last = min(max(last, first + 1), n)
        yield first, last
        first = last


# ---- polynomial hashing modulo 2^64 ---------------------------------------------------------

BASE = 0x9E3779B97F4A7C15


def _odd_inverse(x: int) -> int:
    y = 1
    for _ in range(7):
        y = y * (2 - x * y) % 2**64
    return y


class Powers:
    """Powers of the base and of its inverse, grown as texts need them."""

    def __init__(self) -> None:
        self.reset()

    def reset(self) -> None:
        self.up = self.down = np.ones(1, _U)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << int(n - 1).bit_length()
            for name, b in (("up", BASE), ("down", _odd_inverse(BASE))):
                p = np.full(size, b, _U)
                p[0] = 1
                setattr(self, name, np.multiply.accumulate(p))
        return self.up[:n], self.down[:n]


POWERS = Powers()


def tidy(function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A map over batches that gives the task's memory back when the task ends: Spark uses the same workers for the stages after it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from function(batches)
        finally:
            give_back()

    return run


def give_back() -> None:
    """Return the worker's unused memory, Arrow's and the allocator's, to the system."""
    POWERS.reset()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def prefix_sums(raw: np.ndarray) -> np.ndarray:
    """S with the hash of raw[i:j] as (S[j] - S[i]) * base^(-i), which does not depend on i."""
    _, down = POWERS.get(len(raw) + 1)
    sums = np.zeros(len(raw) + 1, _U)
    with np.errstate(over="ignore"):
        np.cumsum((raw.astype(_U) + _U(1)) * down[: len(raw)], out=sums[1:])
    return sums


def span_hash(sums: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    up, _ = POWERS.get(len(sums))
    with np.errstate(over="ignore"):
        return mix((sums[hi] - sums[lo]) * up[lo] + (hi - lo).astype(_U))


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits that spreads them (the murmur3 finaliser)."""
    with np.errstate(over="ignore"):
        h = h ^ (h >> _U(33))
        h = h * _U(0xFF51AFD7ED558CCD)
        h = h ^ (h >> _U(33))
        h = h * _U(0xC4CEB9FE1A85EC53)
        return h ^ (h >> _U(33))


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of finished steps, which it does when their plans are garbage on the driver."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def group_batches(batches, key: str, rows: int):
    """Arrow tables of whole groups, at least ``rows`` rows each but for the last, from batches sorted by the column key."""
    held: list[pa.RecordBatch] = []
    count = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        count += batch.num_rows
        if count < rows:
            continue
        table = pa.Table.from_batches(held)
        keys = table.column(key).to_numpy()
        cut = int(np.searchsorted(keys, keys[-1], side="left")) if (keys[1:] >= keys[:-1]).all() else int(np.flatnonzero(keys != keys[-1])[-1] + 1) if (keys != keys[-1]).any() else 0
        if cut:
            yield table.slice(0, cut)
            held = [b for b in table.slice(cut).to_batches() if b.num_rows]
            count = table.num_rows - cut
    if count:
        yield pa.Table.from_batches(held)
