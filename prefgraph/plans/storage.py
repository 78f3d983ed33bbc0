"""Tables in the cluster's shared folder, which cut lineage and outlive executors."""

from __future__ import annotations

import contextlib
import re
import tempfile
import uuid
from collections.abc import Iterator

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a table that an algorithm holds is hinted for broadcast (about 32 bytes a row).
BROADCAST_ROWS = 1_000_000

_SCOPES: list[list[tuple[SparkSession, str]]] = []


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where that is unset, a temporary folder in local mode and an error on a cluster, whose machines share no such folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not re.match(r"local($|\[)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir is not set: name a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="prefgraph-")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/")


def store(df: DataFrame, name: str = "table", **told: Column) -> DataFrame:
    """df written to the shared folder and read back. told: aggregates of its rows, which the same job computes; the result's ``told`` has them."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    seen = Observation() if told else None
    (df.observe(seen, *[c.alias(k) for k, c in told.items()]) if told else df).write.parquet(path)
    if _SCOPES:
        _SCOPES[-1].append((spark, path))
    stored = spark.read.schema(df.schema).parquet(path)
    stored.path, stored.told = path, seen.get if told else {}
    return stored


def _delete(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def discard(stored: DataFrame) -> None:
    """Delete a stored table that no result to come reads."""
    _delete(stored.sparkSession, stored.path)
    for scope in _SCOPES:
        scope[:] = [x for x in scope if x[1] != stored.path]


@contextlib.contextmanager
def scratch() -> Iterator[list[DataFrame]]:
    """Tables stored inside are deleted at the end, but for those put into the list that it gives; these belong to the scope around."""
    keep: list[DataFrame] = []
    _SCOPES.append([])
    try:
        yield keep
    finally:
        kept = {x.path for x in keep}
        for spark, path in (own := _SCOPES.pop()):
            if path not in kept:
                _delete(spark, path)
        if _SCOPES:
            _SCOPES[-1].extend(x for x in own if x[1] in kept)


def stored_bytes(stored: DataFrame) -> int:
    spark = stored.sparkSession
    where = spark._jvm.org.apache.hadoop.fs.Path(stored.path)
    return where.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(where).getLength()


def dealt(df: DataFrame, *keys: str) -> DataFrame:
    """df hash-partitioned by keys on the executors' disks: joins on these keys do not move it again, and a lost block is made anew."""
    n = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 8)
    return df.repartition(n, *keys).persist(StorageLevel.DISK_ONLY)


def small(df: DataFrame, rows: int) -> DataFrame:
    """df with a broadcast hint if it has at most the bounded number of rows."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def number(df: DataFrame, order: list[Column], column: str = "id") -> DataFrame:
    """df with dense numbers from 1 in the given order: a range sort and one offset a partition, no single-task window."""
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id())
    stored = store(ranged, "numbered")
    part = F.shiftright("_at", 33)
    starts, total = [], 0
    for p, n in sorted(stored.groupBy(part.alias("p")).count().collect()):
        starts.append((p, total))
        total += n
    offsets = df.sparkSession.createDataFrame(starts, "_p long, _start long")
    place = F.col("_start") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1)) + 1
    return stored.withColumn("_p", part).join(F.broadcast(offsets), "_p").withColumn(column, place).drop("_p", "_at", "_start")


#: Pairs that one task makes.
PAIRS_A_TASK = 4_000_000


def spread_pairs(df: DataFrame, place: str, m: int, both: bool = False) -> DataFrame:
    """Each row of df, numbered from 1 to m by the column place, beside each row numbered above it (or each other row, with both): first, a struct, and the other's columns.

    A row names the places it meets, and these are an equi-join with the numbered rows: as many rows as the result, no Cartesian product,
    and as many tasks as the number of pairs asks for.
    """
    at = F.col(place)
    if both:
        places, within = F.filter(F.sequence(F.lit(1).cast("long"), F.lit(m).cast("long")), lambda i: i != at), F.lit(m > 1)
    else:
        places, within = F.sequence(at + 1, F.lit(m)), at < m
    tasks = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(m, m * m // (1 if both else 2) // PAIRS_A_TASK)) if m > 500 else 1
    ahead = df.filter(within).repartition(tasks, at).select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("first"), F.explode(places).alias(place))
    return ahead.join(small(df, m), place)


def every_pair(df: DataFrame, order: list[Column], both: bool = False) -> DataFrame:
    """(one, two): structs of the rows of df for each pair whose first stands before its second in the order, or for all ordered pairs of different rows."""
    told = store(number(df, order, "_place"), "places", m=F.count(F.lit(1)))
    row = F.struct(*[F.col(f"`{c}`") for c in df.columns])
    return spread_pairs(told, "_place", told.told["m"], both).select(F.col("first").alias("one"), row.alias("two"))
