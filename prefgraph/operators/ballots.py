"""Ballots: weak orders in long form (voter, alt, rank, weight), listed alternatives only; unlisted ones are tied below them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def validate(ballots: DataFrame) -> DataFrame:
    """(voter, alt, problem): pairs listed twice and rows without voter, alternative or rank."""
    missing = ballots.filter(F.col("voter").isNull() | F.col("alt").isNull() | F.col("rank").isNull()).select("voter", "alt", F.lit("missing value").alias("problem"))
    twice = ballots.groupBy("voter", "alt").count().filter("count > 1").select("voter", "alt", F.lit("listed twice").alias("problem"))
    return missing.unionByName(twice)


def from_scores(scores: DataFrame, voter: Column | str, alt: Column | str, score: Column | str, k: int | None = None, dense: bool = False) -> DataFrame:
    """Each voter ranks alternatives by score, the highest first; with k, ranks up to k stay, ties included."""
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    rows = scores.select(as_col(voter).cast("string").alias("voter"), as_col(alt).alias("alt"), as_col(score).alias("_s"))
    order = Window.partitionBy("voter").orderBy(F.desc("_s"))
    ranked = rows.withColumn("rank", (F.dense_rank() if dense else F.rank()).over(order).cast("int"))
    return (ranked if k is None else ranked.filter(F.col("rank") <= k)).select("voter", "alt", "rank", F.lit(1).cast("long").alias("weight"))


def chart_scores(spark: SparkSession, sf_dir: str, period: str = "month", region: str | None = None, alt: str = "l_suppkey", value: str = "sum_qty") -> DataFrame:
    """(voter, alt, score): sums by period and nation of the customer; alt is a key of lineitem, or a column of part or of the supplier's nation."""
    t = {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in ("lineitem", "orders", "customer", "nation", "region", "part", "supplier")}
    nation = t["nation"] if region is None else t["nation"].join(t["region"].filter(F.col("r_name") == region), F.col("n_regionkey") == F.col("r_regionkey"), "left_semi")
    buyers = t["customer"].join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"), "left_semi").select("c_custkey", "c_nationkey")
    day = F.col("o_orderdate")
    when = F.year(day) * 100 + (F.month(day) if period == "month" else F.quarter(day))
    orders = t["orders"].join(buyers, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", F.concat_ws("-", when.cast("string"), F.col("c_nationkey").cast("string")).alias("voter"))
    items = t["lineitem"].select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    if alt.startswith("p_"):
        items = items.join(t["part"].select("p_partkey", alt), F.col("l_partkey") == F.col("p_partkey"))
    elif alt == "s_nationkey":
        items = items.join(t["supplier"].select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    amount = F.col("l_quantity").cast("long") if value == "sum_qty" else F.col("l_extendedprice").cast("decimal(18,2)")
    return items.groupBy("voter", F.col(alt).alias("alt")).agg(F.sum(amount).alias("score"))


def chart_ballots(spark: SparkSession, sf_dir: str, period: str = "month", region: str | None = None, k: int | None = 20, alt: str = "l_suppkey", value: str = "sum_qty") -> DataFrame:
    return from_scores(chart_scores(spark, sf_dir, period, region, alt, value), "voter", "alt", "score", k)


def from_vectors(df: DataFrame, key: str, vector: str) -> DataFrame:
    """Each dimension is a voter that ranks the rows by coordinate, descending."""
    return from_scores(df.select(key, F.posexplode(vector).alias("dim", "x")), "dim", key, "x")


def nest(ballots: DataFrame) -> DataFrame:
    """voter, tiers (array of arrays, best first), weight."""
    tiers = ballots.groupBy("voter", "weight", "rank").agg(F.sort_array(F.collect_list("alt")).alias("tier"))
    return tiers.groupBy("voter", "weight").agg(F.transform(F.sort_array(F.collect_list(F.struct("rank", "tier"))), lambda x: x["tier"]).alias("tiers"))


def unnest(nested: DataFrame) -> DataFrame:
    """Long form of nested ballots; an alternative's rank is one more than the number of those above it."""
    above = F.transform(F.sequence(F.lit(1), F.size("tiers")), lambda i: F.aggregate(F.slice("tiers", F.lit(1), i - 1), F.lit(1), lambda n, t: n + F.size(t)))
    rows = nested.filter(F.size("tiers") > 0).select("voter", "weight", F.explode(F.arrays_zip(above.alias("rank"), F.col("tiers").alias("tier"))).alias("x"))
    return rows.select("voter", F.explode("x.tier").alias("alt"), F.col("x.rank").cast("int").alias("rank"), "weight")


def truncate(ballots: DataFrame, k: int) -> DataFrame:
    return ballots.filter(F.col("rank") <= k)


def restrict(ballots: DataFrame, voters: DataFrame | None = None, alts: DataFrame | None = None) -> DataFrame:
    for keep, c in ((voters, "voter"), (alts, "alt")):
        if keep is not None:
            ballots = ballots.join(keep.select(c).distinct(), c, "left_semi")
    return ballots


def as_of(ballots: DataFrame, ts: Column | str, moment: Column) -> DataFrame:
    """Of each voter the ballot of the latest time not after moment; ts is the column of times."""
    rows = ballots.filter(F.col(ts) <= moment)
    last = rows.groupBy("voter").agg(F.max(ts).alias("_last"))
    return rows.join(last, "voter").filter(F.col(ts) == F.col("_last")).drop("_last")


def by_session(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """A ballot a user and session, ranking event types by count."""
    sessions = events.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.collect_list("event_type").alias("types"))
    counts = sessions.select("s", "user_id", F.explode("types").alias("event_type")).groupBy("s", "user_id", "event_type").count()
    voter = F.concat_ws("-", F.col("user_id").cast("string"), F.unix_timestamp(F.col("s.start")).cast("string"))
    return from_scores(counts, voter, "event_type", "count")


def union(one: DataFrame, two: DataFrame) -> DataFrame:
    return one.withColumn("voter", F.concat(F.lit("1:"), "voter")).unionByName(two.withColumn("voter", F.concat(F.lit("2:"), "voter")))


def with_weights(ballots: DataFrame, weights: DataFrame) -> DataFrame:
    """weights(voter, weight); voters without one weigh 1."""
    given = weights.select("voter", F.col("weight").alias("_w"))
    return ballots.join(given, "voter", "left").withColumn("weight", F.coalesce("_w", F.lit(1))).drop("_w")


def weight_from_json(events: DataFrame, path: str = "$.k") -> DataFrame:
    """(voter, weight): one plus the sum of a number in the events' JSON."""
    return events.groupBy(F.col("user_id").cast("string").alias("voter")).agg((1 + F.coalesce(F.sum(F.get_json_object("props", path).try_cast("long")), F.lit(0))).cast("long").alias("weight"))
