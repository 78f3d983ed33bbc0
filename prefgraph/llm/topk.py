"""Exact top-k by inner product with pivot-table elimination.

The table holds, for every vector, its distances to many pivots. By the triangle inequality, the largest difference of two vectors'
distances to a pivot bounds their distance from below, so (|q|^2 + |x|^2 - bound^2) / 2 bounds their inner product from above.
A query takes the candidates of a block in the order of that bound and stops when its k-th best score is above what is left; the k-th best
score among a bounded sample of rows is a floor that all blocks start from.
Queries and candidates are cut in blocks; each pair of blocks is one bounded group.
Vectors with components beyond LIMIT have no bound: every one of their products is computed, in whole numbers.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import partitions_for

PIVOTS = 48
PIVOT_SAMPLE = 2048  # rows that the pivots are chosen from
QUERY_BLOCK, ROW_BLOCK = 2048, 4096
LIMIT = 1 << 22  # scaled components beyond +-LIMIT could leave the exact range of float64 products
OUT = 1 << 63  # scores from here on are no long
SCALE = 256  # a power of two: scaling is exact


def quantize(vectors: DataFrame) -> DataFrame:
    """vec_id, c (array<int>), f (array<double>): floor(SCALE * x) of each component in c, or, where one leaves +-LIMIT, floor(SCALE * x) / SCALE in f.

    Vectors that are null, empty or hold null or non-finite components take no part. From 2^53 on a component is whole, and f holds it as it is.
    """
    x = F.transform("embedding", lambda x: x.cast("double"))
    size = lambda x: F.abs(x) * SCALE
    finite = F.coalesce(F.forall(x, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))), F.lit(False))
    near = F.forall(x, lambda x: size(x) < LIMIT)
    c = F.when(near, F.transform(x, lambda x: F.floor(x * SCALE)).cast("array<int>"))
    f = F.when(~near, F.transform(x, lambda x: F.when(size(x) < 2.0**53, F.floor(x * SCALE).cast("double") / SCALE).otherwise(x)))
    return vectors.filter(finite & (F.size("embedding") > 0)).select(F.col("vec_id").cast("long").alias("vec_id"), c.alias("c"), f.alias("f")).filter("vec_id is not null")


def sample_rows(vectors: DataFrame, sample: int = PIVOT_SAMPLE) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By dimension, (vec_ids, vectors) of a bounded sample: the first by a hash of the id."""
    rows = vectors.filter("c is not null").orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).collect()
    dims = sorted({len(r.c) for r in rows})
    return {d: (np.array([r.vec_id for r in rows if len(r.c) == d]), np.array([r.c for r in rows if len(r.c) == d], np.float64)) for d in dims}


def choose_pivots(sample: dict[int, tuple[np.ndarray, np.ndarray]], pivots: int = PIVOTS) -> dict[int, np.ndarray]:
    """By dimension, vectors of the sample that lie far from each other."""
    out = {}
    for dim, (_, x) in sample.items():
        x = np.unique(x, axis=0)
        chosen = [int(np.argmax((x * x).sum(axis=1)))]
        near = ((x - x[chosen[0]]) ** 2).sum(axis=1)
        while len(chosen) < min(pivots, len(x)) and near.max() > 0:
            chosen.append(int(np.argmax(near)))
            near = np.minimum(near, ((x - x[chosen[-1]]) ** 2).sum(axis=1))
        out[dim] = x[chosen]
    return out


def pivot_table(vectors: DataFrame, pivots: dict[int, np.ndarray]) -> DataFrame:
    """vec_id, c, f, d: the distances of every vector in c to the pivots of its dimension (none where the sample had no such dimension)."""

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.column("c").to_pylist()
            out: list = [[]] * len(rows)
            for dim in {len(r) for r in rows if r is not None} & set(pivots):
                at = [i for i, r in enumerate(rows) if r is not None and len(r) == dim]
                x, p = np.array([rows[i] for i in at], np.float64), pivots[dim]
                square = (x * x).sum(axis=1)[:, None] + (p * p).sum(axis=1)[None, :] - 2 * x @ p.T
                for i, d in zip(at, np.sqrt(np.maximum(square, 0)), strict=True):
                    out[i] = d
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("c"), batch.column("f"), pa.array(out, pa.list_(pa.float64()))], ["vec_id", "c", "f", "d"])

    return vectors.mapInArrow(measure, "vec_id long, c array<int>, f array<double>, d array<double>")


def with_floor(queries: DataFrame, sample: dict[int, tuple[np.ndarray, np.ndarray]], k: int) -> DataFrame:
    """queries with floor: the k-th best score of a query among the sample's rows, which no row among its k best is below in any block."""

    def floors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = np.full(batch.num_rows, -np.inf)
            rows, ids = batch.column("c").to_pylist(), batch.column("qid").to_numpy()
            for dim in {len(r) for r in rows if r is not None} & set(sample):
                at = np.array([i for i, r in enumerate(rows) if r is not None and len(r) == dim])
                xid, x = sample[dim]
                scores = np.array([rows[i] for i in at], np.float64) @ x.T
                scores[ids[at][:, None] == xid[None, :]] = -np.inf
                if len(xid) >= k:
                    out[at] = np.partition(scores, len(xid) - k, axis=1)[:, len(xid) - k]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out)], [*batch.schema.names, "floor"])

    return queries.mapInArrow(floors, "qid long, c array<int>, f array<double>, d array<double>, floor double")


def search_block(qid: np.ndarray, q: np.ndarray, qd: np.ndarray, xid: np.ndarray, x: np.ndarray, xd: np.ndarray, k: int, floor: np.ndarray | None = None) -> tuple[list[tuple[int, int, int]], int]:
    """The k best (query, row, score) of each query in a block of rows of the same dimension, and the number of scores computed.

    floor: a score for each query that its k best of all blocks reach; rows bounded below it are not computed.
    All numbers are whole and below 2^53, so float64 products are exact; the bounds get a margin above their rounding errors.
    """
    by = np.argsort(xid, kind="stable")
    xid, x, xd = xid[by], x[by], xd[by]
    qn, xn = (q * q).sum(axis=1), (x * x).sum(axis=1)
    out, done = [], 0
    for i in range(len(qid)):
        gap = np.zeros(len(x))
        for p in range(xd.shape[1]):
            np.maximum(gap, np.abs(xd[:, p] - qd[i, p]), out=gap)
        gap = np.maximum(gap - 1e-6 * (1 + gap), 0)
        bound = (qn[i] + xn - gap * gap) / 2
        bound += 1e-9 * (qn[i] + xn) + 1e-3
        bound[xid == qid[i]] = -np.inf
        least = -np.inf if floor is None else floor[i]
        best: list[tuple[float, int]] = []
        order, at, step = np.argsort(-bound, kind="stable"), 0, 32
        while at < len(order) and bound[order[at]] > -np.inf and bound[order[at]] >= (least if len(best) < k else max(least, -best[k - 1][0])):
            chunk = order[at : at + step]
            chunk = chunk[(bound[chunk] > -np.inf) & (bound[chunk] >= least)]
            scores = x[chunk] @ q[i]
            done += len(chunk)
            best = sorted([*best, *zip((-scores).tolist(), xid[chunk].tolist(), strict=True)])[:k]
            at, step = at + step, min(step * 2, 1024)
        out += [(int(qid[i]), v, int(-s)) for s, v in best]
    return out, done


def whole(rows: pd.DataFrame) -> list[list[int]]:
    """The scaled components of c or f as Python integers."""
    scaled = lambda x: int(x * SCALE) if abs(x) < 2.0**60 else int(x) * SCALE
    return [[scaled(x) for x in f] if c is None else [int(x) for x in c] for c, f in zip(rows.c, rows.f, strict=True)]


def search_whole(qid: np.ndarray, q: list[list[int]], xid: np.ndarray, x: list[list[int]], k: int) -> list[tuple[int, int, int]]:
    """As search_block, without bounds and for components of any size: in int64 where no sum can leave it, else in Python integers."""
    largest = lambda rows: max(abs(v) for r in rows for v in r)
    kind = np.int64 if len(q[0]) * max(largest(q), 1) * max(largest(x), 1) < 1 << 63 else object
    table, out = np.array(x, kind), []
    for i, row in zip(qid.tolist(), q, strict=True):
        scores = table @ np.array(row, kind)
        best = heapq.nsmallest(k, ((-s, v) for s, v in zip(scores.tolist(), xid.tolist(), strict=True) if v != i))
        out += [(i, v, -s) for s, v in best]
    return out


def top_k(vectors: DataFrame, is_query: Column, k: int = 5) -> DataFrame:
    """query_id, rank (from 1), vec_id, score (long): the k rows of highest inner product with each query, ties to smaller vec_id.

    vectors(vec_id, embedding); is_query is a condition on vec_id. Rows with the query's own vec_id are no candidates; only vectors of the
    query's dimension are. Rows repeated with one vec_id are candidates of their own, and as a query the first of them counts (by
    components). Rows of a null vec_id take no part. Fewer than k candidates give fewer rows; an empty table gives none. A score among the
    results that is no long is an error.
    """
    fine = quantize(vectors)
    sample = sample_rows(fine)
    table = pivot_table(fine, choose_pivots(sample))
    place = F.coalesce(F.transform("c", lambda x: x.cast("double") / SCALE), "f").alias("e")
    asked = table.filter(is_query).groupBy("vec_id").agg(F.min(F.struct(place, "c", "f", "d")).alias("m")).select(F.col("vec_id").alias("qid"), "m.c", "m.f", "m.d")
    asked = with_floor(asked, sample, k)
    row_blocks = partitions_for(fine.count(), ROW_BLOCK)
    query_blocks = partitions_for(fine.filter(is_query).count(), QUERY_BLOCK)
    rows = table.withColumn("rb", (F.monotonically_increasing_id() % row_blocks).cast("int")).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))))
    asked = asked.withColumn("qb", F.pmod(F.xxhash64("qid"), F.lit(query_blocks)).cast("int")).withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(row_blocks - 1))))

    def search(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        found = []
        length = lambda t: t.c.where(t.c.notna(), t.f).map(len)
        for dim in set(length(left)) & set(length(right)):
            a, b = left[length(left) == dim], right[length(right) == dim]
            near_a, near_b = a[a.c.notna()], b[b.c.notna()]
            if len(near_a) and len(near_b):
                stack = lambda s: np.stack(s.to_numpy()).astype(np.float64).reshape(len(s), -1)
                found += search_block(near_a.qid.to_numpy(), stack(near_a.c), stack(near_a.d), near_b.vec_id.to_numpy(), stack(near_b.c), stack(near_b.d), k, near_a.floor.to_numpy())[0]
            for one, two in ((near_a, b[b.c.isna()]), (a[a.c.isna()], b)):
                if len(one) and len(two):
                    found += search_whole(one.qid.to_numpy(), whole(one), two.vec_id.to_numpy(), whole(two), k)
        held = [Decimal(max(-OUT, min(OUT, s))) for _, _, s in found]  # of scores that are no long only the sign counts
        return pd.DataFrame({"query_id": [x[0] for x in found], "vec_id": [x[1] for x in found], "score": held})

    near = asked.groupBy("qb", "rb").cogroup(rows.groupBy("qb", "rb")).applyInPandas(search, "query_id long, vec_id long, score decimal(20,0)")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    best = near.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)
    score = F.when(F.abs("score") < F.lit(Decimal(OUT)), F.col("score")).otherwise(F.raise_error(F.concat(F.lit("a score of this query is no long: "), F.col("query_id").cast("string"))).cast("decimal(20,0)"))
    return best.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", score.cast("long").alias("score"))


def oracle_sql(every: int = 50, k: int = 5) -> str:
    return f"""
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS c FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, x.vec_id, CAST(list_sum(list_transform(list_zip(q.c, x.c), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v x ON q.vec_id <> x.vec_id WHERE q.vec_id % {every} = 0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INT) AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= {k}
"""
