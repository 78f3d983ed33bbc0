"""Scores on the majority graph, and the order of ids."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.storage import number


def borda(edges: DataFrame, alternatives: DataFrame, src: str = "a", dst: str = "b") -> DataFrame:
    """(alt, borda): the sum of an alternative's margins over all others, 0 without edges."""
    rows = edges.select(F.col(src).alias("alt"), F.col("w").alias("x")).unionByName(edges.select(F.col(dst).alias("alt"), (-F.col("w")).alias("x")))
    rows = rows.unionByName(alternatives.select("alt", F.lit(0).cast(edges.schema["w"].dataType).alias("x")))
    return rows.groupBy("alt").agg(F.sum("x").alias("borda"))


def number_by(scored: DataFrame, order: str = "borda") -> DataFrame:
    """scored(alt, borda, ...) with ids from 1 by borda (descending), borda_asc, key or random; ties by alternative."""
    first = {"borda": [F.desc("borda")], "borda_asc": [F.asc("borda")], "key": [], "random": [F.xxhash64(F.lit(17), "alt")]}[order]
    return number(scored, [*first, F.col("alt")])


def assign_ids(edges: DataFrame, alternatives: DataFrame, order: str = "borda") -> DataFrame:
    """vertices(alt, borda, id) of a graph's alternatives, with ids in the given order (number_by)."""
    return number_by(borda(edges, alternatives), order)


def condorcet_winner(g) -> DataFrame:
    """(id): the alternative that dominates all others, if there is one."""
    m = g.vertices.count()
    if m == 1:
        return g.vertices.select("id")
    return g.edges.groupBy(F.col("src").alias("id")).count().filter(F.col("count") == m - 1).select("id")


def wins(g) -> DataFrame:
    """(id, wins): how many alternatives each dominates."""
    counted = g.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("n"))
    return g.vertices.select("id").join(counted, "id", "left").select("id", F.coalesce("n", F.lit(0)).cast("long").alias("wins"))


def quartile(vertices: DataFrame) -> DataFrame:
    """(alt, quartile) by id. One task sorts the m alternatives, of which there are few against pairs."""
    return vertices.select("alt", F.ntile(4).over(Window.orderBy("id")).cast("int").alias("quartile"))
