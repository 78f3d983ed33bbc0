"""The weighted majority graph as two tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import number, store


@dataclass
class PrefGraph:
    """vertices(alt, id), edges(src, dst, w) by id; w > 0, no loops. Alternatives without edges are in vertices."""

    vertices: DataFrame
    edges: DataFrame

    def induced(self, ids: DataFrame) -> PrefGraph:
        """The subgraph of ids(id)."""
        keep = ids.select(F.col("id").alias("_k")).distinct()
        edges = self.edges.join(keep, F.col("src") == F.col("_k"), "left_semi").join(keep, F.col("dst") == F.col("_k"), "left_semi")
        return PrefGraph(self.vertices.join(keep, F.col("id") == F.col("_k"), "left_semi"), edges)

    def reversed(self) -> PrefGraph:
        return PrefGraph(self.vertices, self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))

    def at_least(self, w, strict: bool = False) -> PrefGraph:
        return PrefGraph(self.vertices, self.edges.filter(F.col("w") > w if strict else F.col("w") >= w))

    def named(self, df: DataFrame, *columns: str) -> DataFrame:
        """df with the alternatives in place of ids in the given columns."""
        for c in columns:
            names = self.vertices.select(F.col("id").alias("_i"), F.col("alt").alias("_alt"))
            df = df.join(names, F.col(c) == F.col("_i")).withColumn(c, F.col("_alt")).drop("_i", "_alt")
        return df


def from_edges(spark, edges: list[tuple], vertices: list | None = None) -> PrefGraph:
    """A graph from literal (src, dst, w); ids are the alternatives."""
    ids = sorted({x for e in edges for x in e[:2]} | set(vertices or []))
    return PrefGraph(spark.createDataFrame([(i, i) for i in ids], "alt long, id long"), spark.createDataFrame(edges, "src long, dst long, w long"))


def two_way(edges: DataFrame) -> dict[str, DataFrame]:
    """Edges in both directions: f along, b against them."""
    return {"f": edges.select("src", "dst", "w"), "b": edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")}


def ranked_weights(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges with ranks from 1 in place of weights, (w, rank) of the distinct weights), stored."""
    ranks = store(number(edges.select("w").distinct(), [F.col("w")], "rank"), "ranks")
    return store(edges.join(ranks, "w").select("src", "dst", F.col("rank").cast("long").alias("w")), "edges"), ranks
