"""Synthetic profiles and graphs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graph import PrefGraph


def sparse_wmg(spark: SparkSession, m: int, density: float, weights: int = 100, seed: int = 1) -> PrefGraph:
    """m vertices; each pair has an edge with the given chance, of random direction and weight 1..weights. Pairs are drawn by rank, not enumerated:
    each vertex draws about density * m / 2 partners."""
    draws = max(1, round(density * m / 2))
    h = lambda *x: F.pmod(F.xxhash64(F.lit(seed), *x), F.lit(2**31))
    pairs = spark.range(1, m + 1).select(F.col("id").alias("x"), F.explode(F.sequence(F.lit(1), F.lit(draws))).alias("k")).select("x", (1 + h(F.col("x"), F.col("k")) % m).alias("y"))
    pairs = pairs.filter("x <> y").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct()
    turn = h(F.col("x"), F.col("y"), F.lit(7)) % 2 == 0
    edges = pairs.select(F.when(turn, F.col("x")).otherwise(F.col("y")).alias("src"), F.when(turn, F.col("y")).otherwise(F.col("x")).alias("dst"), (1 + h(F.col("x"), F.col("y"), F.lit(9)) % weights).cast("long").alias("w"))
    return PrefGraph(spark.range(1, m + 1).select(F.col("id").alias("alt"), "id"), edges)


def mallows(spark: SparkSession, m: int, n: int, phi: float, seed: int = 1) -> DataFrame:
    """Ballots of n voters around the order 1..m (mallows_of)."""
    return mallows_of(spark.range(n), m, phi, seed)


def _uniform(seed: int, ids: np.ndarray, draw: int) -> np.ndarray:
    """Numbers from 0 to 1 that follow from seed, id and draw alone, whatever rows a batch holds: mixed bits of a counter."""
    with np.errstate(over="ignore"):
        z = ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64((seed << 32) + draw)
        for _ in range(2):
            z = (z ^ (z >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return ((z ^ (z >> np.uint64(32))) >> np.uint64(11)).astype(np.float64) / (1 << 53)


def mallows_of(voters: DataFrame, m: int, phi: float, seed: int = 1) -> DataFrame:
    """Ballots of voters(id), from 0, around the order 1..m by repeated insertion: the i-th alternative goes j places above the end with weight phi^j."""

    def draw(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            ids = batch.id.to_numpy()
            rank = np.zeros((len(ids), m), np.int32)
            for i in range(1, m + 1):
                chances = np.cumsum(phi ** np.arange(i))
                up = np.searchsorted(chances[:-1], _uniform(seed, ids, i) * chances[-1], side="right")
                place = (i - up).astype(np.int32)
                rank[:, : i - 1] += rank[:, : i - 1] >= place[:, None]
                rank[:, i - 1] = place
            by = np.argsort(rank, axis=1, kind="stable")
            yield pd.DataFrame({"voter": np.repeat(ids.astype(str), m), "alt": by.ravel() + 1, "rank": np.tile(np.arange(1, m + 1, dtype=np.int32), len(ids))})

    return voters.select(F.col("id").cast("long").alias("id")).mapInPandas(draw, "voter string, alt long, rank int").withColumn("weight", F.lit(1).cast("long"))
