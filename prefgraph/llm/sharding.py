"""Sharding by a keyed Feistel permutation of global row numbers, with cycle walking.

Rows are numbered 0..N-1 in the order of (doc_id, text checksum, size). The permutation maps a number to another
one of 0..N-1; the image p goes to shard ``p % shards`` and slot ``p // shards``. So counts of shards differ by at
most one (law ``rows``), slots have no gaps, and anyone who knows N and the key computes the place of row r
(``place``) or the row at a place (``row_at``) without data.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize

_PRIME = 2147483647  # round values stay below 2^31, so squares fit a signed long
ROUNDS = 6


def _constants(seed: int) -> list[tuple[int, int]]:
    return [((seed * 7919 + 104729 * (i + 1)) % _PRIME, (seed * 6151 + 15485863 * (i + 3)) % _PRIME) for i in range(ROUNDS)]


def domain(n: int) -> tuple[int, int]:
    """Halves a, b with a * b >= n and a * b - n < a, so a walk leaves the range seldom."""
    a = max(1, int(np.ceil(np.sqrt(n))))
    return a, max(1, -(-n // a))


def _spread(x, c: tuple[int, int]):
    y = (x % _PRIME + c[0]) % _PRIME
    y = (y * y + c[1]) % _PRIME
    return (y * y + x % _PRIME * 31) % _PRIME


def _once(p, a: int, b: int, seed: int):
    left, right = p // b, p % b
    for i, c in enumerate(_constants(seed)):
        if i % 2:
            right = (right + _spread(left, c)) % b
        else:
            left = (left + _spread(right, c)) % a
    return left * b + right


def _back(p, a: int, b: int, seed: int):
    left, right = p // b, p % b
    for i, c in reversed(list(enumerate(_constants(seed)))):
        if i % 2:
            right = (right - _spread(left, c)) % b
        else:
            left = (left - _spread(right, c)) % a
    return left * b + right


def _walk(step, numbers: np.ndarray, n: int, seed: int) -> np.ndarray:
    a, b = domain(n)
    out = step(np.asarray(numbers, np.int64), a, b, seed)
    while (far := out >= n).any():
        out[far] = step(out[far], a, b, seed)
    return out


def permute(numbers: np.ndarray, n: int, seed: int = 1) -> np.ndarray:
    return _walk(_once, numbers, n, seed)


def place(row: int, n: int, shards: int, seed: int = 1) -> tuple[int, int]:
    p = int(permute(np.array([row]), n, seed)[0])
    return p % shards, p // shards


def row_at(shard: int, slot: int, n: int, shards: int, seed: int = 1) -> int:
    return int(_walk(_back, np.array([slot * shards + shard]), n, seed)[0])


def number_rows(rows: DataFrame, keys: list[str]) -> tuple[DataFrame, int]:
    """Adds ``row``, the global number in the order of keys, and returns the count.

    One range shuffle of the given (narrow) columns. Equal keys may lie in several ranges: the sort ends on a number of the
    input row, so a key of a third of all rows is split. Offsets of the ranges are one number a partition.
    """
    spark = rows.sparkSession
    order = [*keys, "_in"]
    ranged = rows.withColumn("_in", F.monotonically_increasing_id()).repartitionByRange(*order).sortWithinPartitions(*order)
    stored = materialize(ranged.withColumn("_at", F.monotonically_increasing_id()).drop("_in"), "numbered")
    part = F.shiftright("_at", 33)
    counts = sorted(stored.groupBy(part.alias("p")).count().collect())
    starts, total = [], 0
    for p, c in counts:
        starts.append((p, total))
        total += c
    offsets = spark.createDataFrame(starts, "_p long, _start long")
    joined = stored.withColumn("_p", part).join(F.broadcast(offsets), "_p")  # one row a partition
    low = F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))
    return joined.withColumn("row", F.col("_start") + low).drop("_p", "_at", "_start"), total


def shard_documents(docs: DataFrame, shards: int = 40, seed: int = 1) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of docs(doc_id, text).

    A null text has no bytes (size 16, checksum 0). Null and repeated doc_ids are rows like others; rows equal in doc_id, checksum
    and size are interchangeable. An empty table gives none. Extra columns are ignored. grown_shard is null: under ``rows`` a new
    shard count moves rows everywhere.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text.cast("binary")).cast("long").alias("text_crc32"))
    numbered, n = number_rows(narrow, ["doc_id", "text_crc32", "size"])

    @F.pandas_udf("long")
    def permuted(r: pd.Series) -> pd.Series:
        return pd.Series(permute(r.to_numpy(), n, seed), dtype="int64")

    placed = numbered.withColumn("p", permuted("row"))
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), (F.col("p") % shards).cast("int").alias("shard"),
        F.expr(f"p div {int(shards)}").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )


def oracle_sql(shards: int = 40, seed: int = 1) -> str:
    """The same places by SQL: the walk is a recursive query over the rows that are still outside."""
    spread = lambda x, c: f"((({x} % {_PRIME} + {c[0]}) % {_PRIME}) * (({x} % {_PRIME} + {c[0]}) % {_PRIME}) + {c[1]}) % {_PRIME}"
    def permutation(source: str) -> str:
        sql = f"SELECT k, n, a, b, p // b AS l, p % b AS r FROM {source}"
        for i, c in enumerate(_constants(seed)):
            x, y, m = ("l", "r", "b") if i % 2 else ("r", "l", "a")
            sql = f"SELECT k, n, a, b, {x}, ({y} + (y * y + {x} % {_PRIME} * 31) % {_PRIME}) % {m} AS {y} FROM (SELECT *, {spread(x, c)} AS y FROM ({sql}))"
        return f"SELECT k, n, a, b, l * b + r AS p FROM ({sql})"

    return f"""
WITH RECURSIVE base AS (
  SELECT doc_id, CAST(strlen(coalesce(text, '')) + 16 AS BIGINT) AS size, text FROM documents),
numbered AS (SELECT doc_id, size, text, CAST(row_number() OVER (ORDER BY doc_id) - 1 AS BIGINT) AS k FROM base),
sized AS (SELECT k, n, a, CAST(greatest(1, (n + a - 1) // a) AS BIGINT) AS b, k AS p FROM
  (SELECT k, CAST(count(*) OVER () AS BIGINT) AS n, CAST(greatest(1, ceil(sqrt(count(*) OVER ()))) AS BIGINT) AS a FROM numbered)),
walk AS ({permutation('sized')} UNION ALL {permutation('(SELECT * FROM walk WHERE p >= n)')})
SELECT doc_id, size, 'rows' AS law, CAST(p % {shards} AS INT) AS shard, CAST(p // {shards} AS BIGINT) AS slot, CAST(NULL AS INT) AS grown_shard
FROM walk JOIN numbered USING (k) WHERE p < n
"""
