"""Reading and writing ballots and graphs; schemas are given, never inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import PrefGraph

BALLOTS = "voter string, alt string, rank int, weight long"
EDGES = "src long, dst long, w long"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_ballots(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = BALLOTS) -> DataFrame:
    """Ballots from parquet, orc, csv (with header) or json; a row that does not fit the schema fails the read."""
    reader = spark.read.schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return reader.option("header", "true").format(fmt).load(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_graph(g: PrefGraph, path: str, buckets: int = 16) -> None:
    """Vertices, and edges in two copies: by source and by target, each in folders by hash bucket and sorted within."""
    g.vertices.write.mode("overwrite").parquet(f"{path}/vertices")
    for key in ("src", "dst"):
        bucket = F.pmod(F.hash(key), F.lit(buckets))
        g.edges.withColumn("bucket", bucket).repartition("bucket").sortWithinPartitions("bucket", key).write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/edges_by_{key}")


def read_graph(spark: SparkSession, path: str) -> PrefGraph:
    return PrefGraph(spark.read.parquet(f"{path}/vertices"), spark.read.schema(EDGES).parquet(f"{path}/edges_by_src").select("src", "dst", "w"))


def write_log(rows: list[dict], spark: SparkSession, path: str) -> None:
    spark.createDataFrame(rows).coalesce(1).write.mode("append").json(path)
