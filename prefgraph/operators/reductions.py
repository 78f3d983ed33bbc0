"""Constructions that connect the rules with other problems; tests and data generators."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import every_pair
from .graph import PrefGraph


def reachability_to_wpr(edges: DataFrame, vertices: DataFrame, a: int, b: int) -> PrefGraph:
    """A graph in which a wins, alone, exactly when b is reachable from a in the digraph edges(src, dst) over vertices(id), ids from 0.

    Vertices keep even numbers 2v; midpoints and return vertices get odd ones above them.
    """
    top = 2 * (1 + (vertices.agg(F.max("id")).first()[0] or 0))
    own = edges.select("src", "dst").distinct().filter(f"src <> dst and dst <> {a} and src <> {b}")
    reverse = own.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(True).alias("both"))
    paired = own.join(reverse, ["src", "dst"], "left").withColumn("split", F.col("both") & (F.col("src") < F.col("dst")))
    middle = F.lit(top) + (F.col("src") * top + F.col("dst")) * 2 + 1
    straight = paired.filter("split is null or not split").select((F.col("src") * 2).alias("src"), (F.col("dst") * 2).alias("dst"), F.lit(4).alias("w"))
    split = paired.filter("split").select((F.col("src") * 2).alias("x"), (F.col("dst") * 2).alias("y"), middle.alias("m"))
    halves = split.select(F.col("x").alias("src"), F.col("m").alias("dst"), F.lit(4).alias("w")).unionByName(split.select(F.col("m").alias("src"), F.col("y").alias("dst"), F.lit(4).alias("w")))
    back = vertices.filter(F.col("id") != b).select((F.col("id") * 2).alias("u"), (F.col("id") * 2 + 1).alias("r"))
    for_mid = split.select(F.col("m").alias("u"), (F.col("m") + 1).alias("r"))
    back = back.unionByName(for_mid)
    into = back.select(F.lit(2 * b).cast("long").alias("src"), F.col("r").alias("dst"), F.lit(4).alias("w"))
    out = back.select(F.col("r").alias("src"), F.col("u").alias("dst"), F.when(F.col("u") == 2 * a, 2).otherwise(4).alias("w"))
    all_edges = straight.unionByName(halves).unionByName(into).unionByName(out).select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("w").cast("long").alias("w"))
    ids = vertices.select((F.col("id") * 2).alias("id")).unionByName(back.select(F.col("r").alias("id"))).unionByName(for_mid.select(F.col("u").alias("id"))).distinct()
    return PrefGraph(ids.select(F.col("id").cast("long").alias("alt"), F.col("id").cast("long").alias("id")), all_edges)


def emas_to_ranked_pairs(edges: DataFrame, f: int) -> tuple[DataFrame, DataFrame]:
    """(margins, tie order) in which 0 wins ranked pairs exactly when the edge of place f is not in the edge-maximal acyclic subgraph.

    edges(ord, src, dst): ord from 1, vertices from 1, no loops or antiparallel edges.
    """
    m = edges.count()
    weight = (F.lit(m + 1) - F.col("ord")).cast("long")
    chosen = edges.filter(F.col("ord") == f)
    up = edges.filter(F.col("ord") != f).select(F.col("src").alias("a"), F.col("dst").alias("b"), weight.alias("margin"))
    up = up.unionByName(chosen.select(F.col("src").alias("a"), F.lit(0).cast("long").alias("b"), weight.alias("margin")))
    up = up.unionByName(chosen.select(F.lit(0).cast("long").alias("a"), F.col("dst").alias("b"), F.lit(m + 1).cast("long").alias("margin")))
    ids = edges.select(F.col("src").alias("v")).unionByName(edges.select(F.col("dst").alias("v"))).distinct().unionByName(edges.sparkSession.createDataFrame([(0,)], "v long"))
    pairs = every_pair(ids, [F.col("v")], both=True).select(F.col("one.v").alias("a"), F.col("two.v").alias("b"), F.lit(0).cast("long").alias("margin"))
    signed = up.unionByName(up.select(F.col("b").alias("a"), F.col("a").alias("b"), (-F.col("margin")).alias("margin"))).unionByName(pairs)
    return signed.groupBy("a", "b").agg(F.sum("margin").cast("long").alias("margin")), ids.select(F.col("v").alias("alt"), F.col("v").alias("pos"))


def realise_profile(g: PrefGraph) -> DataFrame:
    """Ballots whose majority graph is g (even weights): for each edge w / 2 pairs of linear orders that agree on that edge and cancel elsewhere."""
    alts = g.vertices.select(F.sort_array(F.collect_set("id")).alias("all"))
    each = g.edges.withColumn("copy", F.explode(F.sequence(F.lit(1), (F.col("w") / 2).cast("int")))).join(F.broadcast(alts), F.lit(True))
    rest = F.filter("all", lambda x: (x != F.col("src")) & (x != F.col("dst")))
    name = lambda side: F.concat_ws("-", F.col("src").cast("string"), F.col("dst").cast("string"), F.col("copy").cast("string"), F.lit(side))
    one = each.select(name("x").alias("voter"), F.concat(F.array("src", "dst"), rest).alias("line"))
    two = each.select(name("y").alias("voter"), F.concat(F.reverse(rest), F.array("src", "dst")).alias("line"))
    lines = one.unionByName(two).select("voter", F.posexplode("line").alias("p", "alt"))
    return lines.select("voter", "alt", (F.col("p") + 1).cast("int").alias("rank"), F.lit(1).cast("long").alias("weight"))
