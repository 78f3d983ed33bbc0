"""Connected components by alternating large and small stars on a stored edge table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, release


def _star(edges: DataFrame, small: bool) -> DataFrame:
    """One star step: neighbours move to the least node near them. Minima are partial sums; the join back is of stored tables where it can be."""
    both = edges if small else edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
    least = materialize(least.select(F.col("a").alias("_a"), "m"), "star")
    met = both.join(least, both.a == least._a)
    out = met.filter(F.col("b") != F.col("m")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    if small:
        out = out.unionByName(least.filter("_a <> m").select(F.col("_a").alias("a"), F.col("m").alias("b")))
    else:
        out = out.filter("a > b")
        own = edges.join(least, edges.a == least._a).filter("a <> m").select("a", F.col("m").alias("b"))
        out = out.unionByName(own)
    return out.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for every node of edges(a, b), both long: root is the least node of its component. Loops and repeated edges are fine."""
    now = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct()
    now = materialize(now, "edges")
    state = None
    while True:
        large = materialize(_star(now, small=False), "edges")
        after = materialize(_star(large, small=True), "edges")
        found = after.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).collect()[0]
        discard(now)
        discard(large)
        release(now.sparkSession)
        now = after
        if tuple(found) == state:
            break
        state = tuple(found)
    roots = now.select("b").distinct()
    return materialize(now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots.select(F.col("b").alias("node"), F.col("b").alias("root"))), "components")
