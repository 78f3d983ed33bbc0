"""Majority margins from listed pairs only.

With C(a, b) the signed sum over voters that list both, and n_x the weight of voters that list x, the margin of a over b with unlisted
alternatives tied last is C(a, b) + n_a - n_b. So pairs are built inside ballots, and the dense part is a difference of two numbers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from ..plans.storage import every_pair, number, scratch, small, spread_pairs, store
from .graph import PrefGraph
from .scores import assign_ids, number_by


def _listed_pairs(ballots: DataFrame) -> DataFrame:
    """Pairs a < b that a voter lists, with both ranks."""
    one = ballots.select("voter", F.col("alt").alias("a"), F.col("rank").alias("ra"), F.col("weight").alias("wv"))
    two = ballots.select("voter", F.col("alt").alias("b"), F.col("rank").alias("rb"))
    return one.join(two, "voter").filter("a < b")


def _both_ways(half: DataFrame) -> DataFrame:
    return half.unionByName(half.select(F.col("b").alias("a"), F.col("a").alias("b"), (-F.col("margin")).alias("margin")))


def _total(x: Column, ballots: DataFrame) -> Column:
    """The sum of weights: a long where weights are whole numbers, else in their own type."""
    return F.sum(x).cast("long") if isinstance(ballots.schema["weight"].dataType, IntegralType) else F.sum(x)


def appearances(ballots: DataFrame) -> DataFrame:
    return ballots.groupBy("alt").agg(_total(F.col("weight"), ballots).alias("n"))


def _every_pair(ballots: DataFrame) -> DataFrame:
    """(a, b, base) for all a < b: base is n_a - n_b."""
    return every_pair(appearances(ballots), [F.col("alt")]).select(F.col("one.alt").alias("a"), F.col("two.alt").alias("b"), (F.col("one.n") - F.col("two.n")).alias("base"))


def pairwise_counts(ballots: DataFrame, unlisted: str = "last") -> DataFrame:
    """(a, b, prefer): weight of voters with a above b, of all ordered pairs that some voter prefers."""
    both = _listed_pairs(ballots)
    w = F.col("wv")
    listed = both.filter("ra < rb").select("a", "b", w.alias("prefer")).unionByName(both.filter("rb < ra").select(F.col("b").alias("a"), F.col("a").alias("b"), w.alias("prefer")))
    if unlisted == "ignore":
        return listed.groupBy("a", "b").agg(F.sum("prefer").cast("long").alias("prefer"))
    together = both.groupBy("a", "b").agg(F.sum("wv").alias("t"))
    gone = together.select("a", "b", (-F.col("t")).alias("prefer")).unionByName(together.select(F.col("b").alias("a"), F.col("a").alias("b"), (-F.col("t")).alias("prefer")))
    n = appearances(ballots)
    pairs = _every_pair(ballots).select("a", "b")
    pairs = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    alone = pairs.join(n.select(F.col("alt").alias("a"), F.col("n").alias("prefer")), "a").select("a", "b", "prefer")
    return listed.unionByName(gone).unionByName(alone).groupBy("a", "b").agg(F.sum("prefer").cast("long").alias("prefer")).filter("prefer > 0")


def _co_listed(ballots: DataFrame) -> DataFrame:
    """(a, b, margin) with a < b, from the voters that list both."""
    sign = F.signum(F.col("rb") - F.col("ra")).cast("int")
    return _listed_pairs(ballots).groupBy("a", "b").agg(_total(F.col("wv") * sign, ballots).alias("margin"))


def half_margins(ballots: DataFrame, unlisted: str = "last") -> DataFrame:
    """(a, b, margin) of all pairs a < b (of co-listed pairs only with unlisted="ignore")."""
    listed = _co_listed(ballots)
    if unlisted == "ignore":
        return listed
    met = _every_pair(ballots).join(listed.withColumnRenamed("margin", "c"), ["a", "b"], "left")
    return met.select("a", "b", (F.col("base") + F.coalesce("c", F.col("base") * 0)).alias("margin"))


def majority_margins(ballots: DataFrame, unlisted: str = "last") -> DataFrame:
    """(a, b, margin) of all ordered pairs (of co-listed pairs only with unlisted="ignore")."""
    return _both_ways(half_margins(ballots, unlisted))


def head_to_head(ballots: DataFrame) -> DataFrame:
    return majority_margins(ballots, "ignore")


def add(one: DataFrame, two: DataFrame) -> DataFrame:
    """Margins of two profiles over the same alternatives together."""
    return one.unionByName(two).groupBy("a", "b").agg(F.sum("margin").cast("long").alias("margin"))


def _every_pair_by_group(ballots: DataFrame, group: str) -> DataFrame:
    """(g, group, a, b, margin) for all a < b that appear at the same level: n_a - n_b of that level. As _every_pair, with a run of numbers a level."""
    n = ballots.rollup("alt", group).agg(F.sum("weight").cast("long").alias("n"), F.grouping_id().alias("g")).filter("g <= 1")
    told = store(number(n, [F.col("g"), F.col(group), F.col("alt")], "at"), "appearances")
    ends = told.groupBy("g", F.col(group).alias("_of")).agg(F.max("at").alias("end"), F.count(F.lit(1)).alias("m"))
    ahead = told.join(ends.withColumnRenamed("g", "_g"), (F.col("g") == F.col("_g")) & F.col(group).eqNullSafe(F.col("_of"))).filter("at < end")
    ahead = ahead.select("g", group, F.col("alt").alias("a"), F.col("n").alias("na"), F.explode(F.sequence(F.col("at") + 1, F.col("end"))).alias("at"))
    return ahead.join(small(told.select("at", F.col("alt").alias("b"), "n"), told.count()), "at").select("g", group, "a", "b", (F.col("na") - F.col("n")).alias("margin"))


def by_group(ballots: DataFrame, group: str, unlisted: str = "last") -> DataFrame:
    """(group, a, b, margin) with a < b, for each group of voters and for all together (group null), over the alternatives that the level lists.

    With unlisted="ignore" only voters that list both count, and only pairs that some voter of the level lists together are given.
    """
    one = ballots.select("voter", group, F.col("alt").alias("a"), F.col("rank").alias("ra"), "weight")
    two = ballots.select("voter", F.col("alt").alias("b"), F.col("rank").alias("rb"))
    sign = F.signum(F.col("rb") - F.col("ra")).cast("long")
    rolled = one.join(two, "voter").filter("a < b").rollup("a", "b", group).agg(F.sum(F.col("weight") * sign).cast("long").alias("margin"), F.grouping_id().alias("g"))
    listed = rolled.filter("g <= 1").select("g", group, "a", "b", "margin")
    if unlisted == "ignore":
        return listed.drop("g")
    both = listed.unionByName(_every_pair_by_group(ballots, group)).groupBy("g", group, "a", "b")
    return both.agg(F.sum("margin").cast("long").alias("margin")).drop("g")


def dominance(margins: DataFrame) -> DataFrame:
    return margins.filter("margin > 0").select("a", "b")


def weighted_majority_graph(margins: DataFrame, alternatives: DataFrame, order: str = "borda") -> PrefGraph:
    """The graph of positive margins over alternatives(alt), stored, with ids in the given order (scores.assign_ids)."""
    edges = store(margins.filter("margin > 0").select("a", "b", F.col("margin").alias("w")), "margins")
    vertices = store(assign_ids(edges, alternatives, order), "vertices")
    m = vertices.count()
    names = small(vertices.select("alt", "id"), m)
    ids = edges.join(names.select(F.col("alt").alias("a"), F.col("id").alias("src")), "a").join(names.select(F.col("alt").alias("b"), F.col("id").alias("dst")), "b")
    return PrefGraph(vertices, store(ids.select("src", "dst", "w"), "edges"))


def graph_of(ballots: DataFrame, order: str = "borda", unlisted: str = "last") -> PrefGraph:
    """The weighted majority graph of ballots, stored. No pair is shuffled while what voters list together fits a broadcast.

    An alternative's sum of margins follows from its own appearances, all appearances and its listed pairs, so ids come first and each
    edge is made once, with its ids, in its direction.
    """
    with scratch() as keep:
        listed = store(_co_listed(ballots), "listed", n=F.count(F.lit(1)))
        count = store(appearances(ballots), "appearances", m=F.count(F.lit(1)), total=F.sum("n"))
        m, total = count.told["m"], count.told["total"]
        base = F.col("n") * F.lit(m) - F.lit(total) if unlisted == "last" else F.col("n") * 0
        signed = listed.select(F.col("a").alias("alt"), F.col("margin").alias("x")).unionByName(listed.select(F.col("b").alias("alt"), (-F.col("margin")).alias("x")))
        scored = count.join(signed.groupBy("alt").agg(F.sum("x").alias("x")), "alt", "left").select("alt", "n", (base + F.coalesce("x", F.col("n") * 0)).alias("borda"))
        named = store(number_by(scored, order), "vertices")
        vertices = store(named.select("alt", "borda", "id"), "vertices")
        of = lambda end: small(named.select(F.col("alt").alias(end), F.col("id").alias(f"i{end}")), m)
        ahead = F.col("ia") < F.col("ib")
        told = listed.join(of("a"), "a").join(of("b"), "b").select(F.least("ia", "ib").alias("one"), F.greatest("ia", "ib").alias("two"), F.when(ahead, F.col("margin")).otherwise(-F.col("margin")).alias("c"))
        if unlisted == "ignore":
            pairs = told.withColumnRenamed("c", "w")
        else:
            every = spread_pairs(named.select("id", "n"), "id", m).select(F.col("first.id").alias("one"), (F.col("first.n") - F.col("n")).alias("base"), F.col("id").alias("two"))
            pairs = every.join(small(store(told, "listed"), listed.told["n"]), ["one", "two"], "left").select("one", "two", (F.col("base") + F.coalesce("c", F.col("base") * 0)).alias("w"))
        forth = F.col("w") > 0
        kind = "long" if isinstance(ballots.schema["weight"].dataType, IntegralType) else ballots.schema["weight"].dataType
        edges = pairs.filter("w <> 0").select(F.when(forth, F.col("one")).otherwise(F.col("two")).alias("src"), F.when(forth, F.col("two")).otherwise(F.col("one")).alias("dst"), F.abs("w").cast(kind).alias("w"))
        edges = store(edges, "edges", n=F.count(F.lit(1)))
        keep += [vertices, edges]
    return PrefGraph(vertices, edges)
