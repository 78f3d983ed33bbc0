"""Reachability, strongly connected components, the Schwartz set and the uncovered set."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import store
from .graph import PrefGraph


def reachable(g: PrefGraph, a: int, b: int) -> bool:
    from .paths import wide_path_exists

    return wide_path_exists(g, a, b, 0, strict=True)


def strongly_connected(g: PrefGraph) -> DataFrame:
    """(id, scc): scc is the least id of the component. Vertices whose least ids forward and backward are one have found theirs; the others
    go on among themselves."""
    from ..plans.winners import UNKNOWN, label_pass

    left, edges, found = store(g.vertices.select("id", F.lit(UNKNOWN).alias("status")), "left"), g.edges.select("src", "dst", F.lit(1).cast("long").alias("w")), None
    while not left.isEmpty():
        labels = label_pass(left, edges)
        done = labels.filter("s = t").select("id", F.col("s").alias("scc"))
        found = done if found is None else found.unionByName(done)
        rest = labels.filter("s <> t")
        left = store(rest.select("id", "status"), "left")
        side = lambda end: rest.select(F.col("id").alias(end), F.col("s").alias(f"{end}_s"), F.col("t").alias(f"{end}_t"))  # noqa: B023, E731
        edges = store(edges.join(side("src"), "src").join(side("dst"), "dst").filter("src_s = dst_s and src_t = dst_t").select("src", "dst", "w"), "edges")
    return g.vertices.select("id", F.col("id").alias("scc")).limit(0) if found is None else found


def schwartz_set(g: PrefGraph) -> DataFrame:
    """(id): the union of the components without an edge from outside."""
    scc = store(strongly_connected(g), "scc")
    a, b = scc.select(F.col("id").alias("src"), F.col("scc").alias("sa")), scc.select(F.col("id").alias("dst"), F.col("scc").alias("sb"))
    dominated = g.edges.join(a, "src").join(b, "dst").filter("sa <> sb").select(F.col("sb").alias("scc")).distinct()
    return scc.join(dominated, "scc", "left_anti").select("id")


def uncovered_set(g: PrefGraph) -> DataFrame:
    """(id): the alternatives that none covers; b covers a if it dominates a and all that a dominates.

    Such a b dominates more than a does: only those edges are joined with what a dominates. That takes up to m^3 / 6 rows before they are counted.
    """
    edges = g.edges.select("src", "dst")
    wins = edges.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    above = edges.join(wins.select("src", F.col("n").alias("more")), "src").join(wins.select(F.col("src").alias("dst"), "n"), "dst", "left").select("src", "dst", "more", F.coalesce("n", F.lit(0)).alias("n")).filter("more > n")
    beyond = above.filter("n > 0").join(edges.select(F.col("src").alias("dst"), F.col("dst").alias("third")), "dst")
    both = beyond.join(edges.select("src", F.col("dst").alias("third")), ["src", "third"]).groupBy("src", "dst", "n").agg(F.count(F.lit(1)).alias("both"))
    covered = both.filter("both = n").select("dst").unionByName(above.filter("n = 0").select("dst"))
    return g.vertices.select("id").join(covered, F.col("id") == F.col("dst"), "left_anti")
