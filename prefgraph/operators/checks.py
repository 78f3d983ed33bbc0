"""Comparisons of results, and transforms of profiles behind the axioms."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import every_pair


def diff(one: DataFrame, two: DataFrame) -> DataFrame:
    """Rows of only one of two tables of the same columns, with side."""
    return one.exceptAll(two).withColumn("side", F.lit("left")).unionByName(two.exceptAll(one).withColumn("side", F.lit("right")))


def kendall(one: DataFrame, two: DataFrame) -> DataFrame:
    """(agree, disagree, tied) over pairs of alternatives of two rankings(alt, rnk)."""
    r = one.select("alt", F.col("rnk").alias("r1")).join(two.select("alt", F.col("rnk").alias("r2")), "alt")
    pairs = every_pair(r, [F.col("alt")]).select("one.r1", "one.r2", F.col("two.r1").alias("s1"), F.col("two.r2").alias("s2"))
    sign = F.signum(F.col("r1") - F.col("s1")) * F.signum(F.col("r2") - F.col("s2"))
    n = lambda c: F.coalesce(F.sum(F.when(c, 1)), F.lit(0)).cast("long")
    return pairs.agg(n(sign > 0).alias("agree"), n(sign < 0).alias("disagree"), n(sign == 0).alias("tied"))


def clone(ballots: DataFrame, alt, twin) -> DataFrame:
    """A second alternative directly below alt on every ballot that lists it."""
    spread = ballots.withColumn("rank", F.col("rank") * 2)
    return spread.unionByName(spread.filter(F.col("alt") == F.lit(alt)).withColumn("alt", F.lit(twin)).withColumn("rank", F.col("rank") + 1))


def raise_alternative(ballots: DataFrame, alt) -> DataFrame:
    """alt one place higher on linear ballots."""
    at = ballots.filter(F.col("alt") == F.lit(alt)).select("voter", F.col("rank").alias("_r"))
    rank = F.when((F.col("alt") == F.lit(alt)) & (F.col("_r") > 1), F.col("rank") - 1).when(F.col("rank") == F.col("_r") - 1, F.col("rank") + 1).otherwise(F.col("rank"))
    return ballots.join(at, "voter", "left").withColumn("rank", rank.cast("int")).drop("_r")
