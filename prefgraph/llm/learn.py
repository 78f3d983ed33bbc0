"""Labelled samples of a bounded size and a small solver for smooth convex losses."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def minimize(loss: Callable[[np.ndarray], tuple[float, np.ndarray]], start: np.ndarray, steps: int = 60, memory: int = 8, tolerance: float = 1e-5) -> np.ndarray:
    """Limited-memory quasi-Newton descent with backtracking; loss gives value and gradient."""
    x = start.astype(np.float64)
    value, grad = loss(x)
    pairs: list[tuple[np.ndarray, np.ndarray, float]] = []
    for _ in range(steps):
        if np.abs(grad).max() < tolerance:
            break
        d, kept = grad.copy(), []
        for s, y, rho in reversed(pairs):
            kept.append(a := rho * (s @ d))
            d -= a * y
        if pairs:
            s, y, _ = pairs[-1]
            d *= (s @ y) / (y @ y)
        else:
            d /= max(1.0, float(np.linalg.norm(grad)))
        for (s, y, rho), a in zip(pairs, reversed(kept), strict=True):
            d += (a - rho * (y @ d)) * s
        slope, size = float(grad @ d), 1.0
        if slope <= 0:
            pairs, d, slope = [], grad.copy(), float(grad @ grad)
        for _ in range(25):
            new_value, new_grad = loss(x - size * d)
            if new_value <= value - 1e-4 * size * slope:
                break
            size /= 2
        else:
            break
        s, y = -size * d, new_grad - grad
        if (sy := float(s @ y)) > 1e-12:
            pairs = [*pairs[-(memory - 1) :], (s, y, 1.0 / sy)]
        x, value, grad = x + s, new_value, new_grad
    return x


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 0.5 * (1.0 + np.tanh(0.5 * np.asarray(z, np.float64)))


def fold(doc_id, folds: int):
    """crc32 of the id's text, modulo folds; null for a null id."""
    return (F.crc32(doc_id.cast("long").cast("string").cast("binary")) % folds).cast("int")


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, use, rows: int, size: int | None = None) -> tuple[DataFrame, dict[int, int]]:
    """(text, y) of at most ``rows`` labelled documents, half of each class where there are enough, and the counts of all usable labels by class.

    The sample is the first labels by a hash of doc_id, and with size only up to so many bytes of text in each class (one text at least); use is a condition on doc_id. Null ids and labels other than 0 and 1 take no part.
    """
    usable = labels.select(F.col("doc_id").cast("long").alias("_id"), F.col(label).cast("int").alias("y")).filter(F.col("_id").isNotNull() & F.col("y").isin(0, 1) & use(F.col("_id")))
    counts = {r.y: r["n"] for r in usable.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    few = None
    for y in (0, 1):
        part = usable.filter(F.col("y") == y).orderBy(F.xxhash64("_id"), "_id").limit(rows // 2)
        few = part if few is None else few.unionByName(part)
    few = few.groupBy("_id").agg(F.max("y").alias("y"))
    if size is not None:  # a window over at most ``rows`` narrow rows and their repeats
        lengths = docs.select(F.col("doc_id").cast("long").alias("_id"), F.octet_length("text").alias("_n")).join(F.broadcast(few), "_id").groupBy("_id", "y").agg(F.sum(F.coalesce("_n", F.lit(0))).alias("_n"))
        before = F.sum("_n").over(Window.partitionBy("y").orderBy(F.xxhash64("_id"), "_id").rowsBetween(Window.unboundedPreceding, -1))
        few = lengths.withColumn("_before", F.coalesce(before, F.lit(0))).filter((F.col("_before") == 0) | (F.col("_before") + F.col("_n") <= size // 2)).select("_id", "y")
    return docs.select(F.col("doc_id").cast("long").alias("_id"), F.col("text").alias("text")).join(F.broadcast(few), "_id").select("text", "y"), counts
