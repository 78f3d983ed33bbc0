"""The widest-path rule by its definition: a beats b if its widest path to b is wider than b's to a. Ties are not transitive."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..plans.storage import discard, every_pair, small, store
from .graph import PrefGraph
from .paths import widest_both


def beats(p: DataFrame) -> DataFrame:
    """(a, b) with a wider path a to b than back, from widths p(a, b, width)."""
    back = p.select(F.col("b").alias("a"), F.col("a").alias("b"), F.col("width").alias("back"))
    return p.join(back, ["a", "b"], "left").filter(F.col("width") > F.coalesce("back", F.lit(0))).select("a", "b")


def winners_exact(p: DataFrame, vertices: DataFrame) -> DataFrame:
    return vertices.select("id").join(beats(p).select(F.col("b").alias("id")), "id", "left_anti")


def counted(p: DataFrame, vertices: DataFrame) -> DataFrame:
    """(id, beaten_by, beats) of vertices(id, size), each of which stands for so many alternatives."""
    b = store(beats(p), "beats")
    size = lambda end: vertices.select(F.col("id").alias(end), "size")
    lost = b.join(size("a"), "a").groupBy(F.col("b").alias("id")).agg(F.sum("size").alias("beaten_by"))
    won = b.join(size("b"), "b").groupBy(F.col("a").alias("id")).agg(F.sum("size").alias("beats"))
    return vertices.select("id").join(lost, "id", "left").join(won, "id", "left").select("id", F.coalesce("beaten_by", F.lit(0)).cast("long").alias("beaten_by"), F.coalesce("beats", F.lit(0)).cast("long").alias("beats"))


def ranked(each: DataFrame) -> DataFrame:
    """each(..., beaten_by) with rnk, one more than the number of rows beaten by fewer.

    Ranks are made on the distinct counts, which are joined back, so no task sorts all alternatives.
    """
    tiers = each.groupBy("beaten_by").agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(Window.orderBy("beaten_by").rowsBetween(Window.unboundedPreceding, -1))
    ranks = tiers.select("beaten_by", (1 + F.coalesce(before, F.lit(0))).cast("long").alias("rnk"))
    return each.join(ranks, "beaten_by").select(*each.columns, "rnk")


def ranking(p: DataFrame, vertices: DataFrame) -> DataFrame:
    """(id, beaten_by, beats, rnk): by how many alternatives beat it, which extends the strict order."""
    return ranked(counted(p, vertices.select("id", F.lit(1).alias("size"))))


def relation(p: DataFrame, vertices: DataFrame) -> DataFrame:
    """(a, b) of the relation "at least as good", without (a, a): all pairs but those where b beats a. Quadratic, as the relation is."""
    pairs = every_pair(vertices.select("id"), [F.col("id")], both=True).select(F.col("one.id").alias("a"), F.col("two.id").alias("b"))
    return pairs.join(beats(p).select(F.col("b").alias("a"), F.col("a").alias("b")), ["a", "b"], "left_anti")


def _against(g: PrefGraph, c: int) -> DataFrame:
    """(id, out, back): widths from c to every other alternative and back, 0 without a path."""
    found = widest_both(g, g.vertices.filter(F.col("id") == c).select("id"))
    others = g.vertices.filter(F.col("id") != c).select("id")
    return others.join(found, "id", "left").select("id", F.coalesce("out", F.lit(0)).alias("out"), F.coalesce("back", F.lit(0)).alias("back"))


def is_winner(g: PrefGraph, c: int) -> tuple[bool, DataFrame]:
    """Whether c wins, and the alternatives that beat it: two single-source searches."""
    worse = store(_against(g, c).filter("back > out").select("id"), "beaten")
    return worse.isEmpty(), worse


def is_unique_winner(g: PrefGraph, c: int) -> bool:
    return _against(g, c).filter("back >= out").isEmpty()


def top_k(g: PrefGraph, k: int, mode: str = "remove", find=None) -> DataFrame:
    """(tier, id) of at least k alternatives, ties kept. remove: winners are deleted and the rest is decided anew; ranking: tiers on the
    full graph. The two can differ."""
    from ..plans.winners import find_winners
    from .paths import all_pairs_widest

    if mode == "ranking":
        r = ranking(all_pairs_widest(g), g.vertices)
        return r.filter(F.col("rnk") <= k).select(F.dense_rank().over(Window.orderBy("rnk")).cast("int").alias("tier"), "id")
    find, rest, found, tier = find or find_winners, g, None, 0
    have = 0
    while have < k:
        won = store(find(rest).winners.select(F.lit(tier + 1).alias("tier"), "id"), "tier", n=F.count(F.lit(1)))
        if not won.told["n"]:
            break
        tier, have = tier + 1, have + won.told["n"]
        found = won if found is None else found.unionByName(won)
        gone = lambda end: small(won.select(F.col("id").alias(end)), won.told["n"])  # noqa: B023, E731
        after = PrefGraph(store(rest.vertices.join(gone("id"), "id", "left_anti"), "rest"), store(rest.edges.join(gone("src"), "src", "left_anti").join(gone("dst"), "dst", "left_anti").select("src", "dst", "w"), "rest"))
        if tier > 1:
            discard(rest.vertices)
            discard(rest.edges)
        rest = after
    return g.vertices.select(F.lit(0).alias("tier"), "id").limit(0) if found is None else found


def describe(winners: DataFrame, dimension: DataFrame, key: str) -> DataFrame:
    """Attributes of winning alternatives(alt) from a dimension table."""
    return F.broadcast(winners.select(F.col("alt").alias(key))).join(dimension, key)
