"""SQL surface: views of a graph and its winners, and a table function on nested ballots."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .operators.graph import PrefGraph
from .plans.winners import find_winners


@udtf(returnType="above string, below string")
class BallotPairs:
    """Ordered pairs of one nested ballot."""

    def eval(self, tiers: list):
        for i, tier in enumerate(tiers or []):
            for lower in (tiers or [])[i + 1 :]:
                for a in tier:
                    for b in lower:
                        yield str(a), str(b)


def register(spark: SparkSession, g: PrefGraph) -> None:
    """Views wmg_vertices, wmg_edges and wpr_winners, and the function ballot_pairs(tiers)."""
    g.vertices.createOrReplaceTempView("wmg_vertices")
    g.edges.createOrReplaceTempView("wmg_edges")
    g.vertices.join(find_winners(g).winners, "id", "left_semi").createOrReplaceTempView("wpr_winners")
    spark.udtf.register("ballot_pairs", BallotPairs)
