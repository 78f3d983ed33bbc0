"""Pairs of alternatives from pairs of classes that all voters rank alike, beside the whole tables."""

import random

from pyspark.sql import functions as F

from prefgraph.operators import margins as mg
from prefgraph.operators import paths
from prefgraph.plans import alike
from test_one_task import _profile


def _rows(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


def _ballots(spark, seed):
    _, rows = _profile(random.Random(seed), 3)
    return spark.createDataFrame(rows, "voter string, alt long, rank int, weight long")


def test_margins_by_group_from_classes(spark, monkeypatch):
    whole, asked = mg.by_group, []
    monkeypatch.setattr(mg, "by_group", lambda b, group: asked.append(b.select("alt").distinct().count()) or whole(b, group))
    for seed in (1, 2):
        b = _ballots(spark, seed).withColumn("side", F.when(F.col("voter") < "v2", "one").otherwise("two"))
        assert _rows(alike.margins_by_group(b, "side").select("side", "a", "b", "margin")) == _rows(whole(b, "side").select("side", "a", "b", "margin"))
        assert asked.pop() * 3 <= b.select("alt").distinct().count()


def test_widest_paths_from_classes(spark, monkeypatch):
    whole, asked = paths.all_pairs_widest, []
    monkeypatch.setattr(paths, "all_pairs_widest", lambda g, method: asked.append(g.vertices.count()) or whole(g, method))
    for seed in (1, 2):
        b = _ballots(spark, seed).withColumn("weight", (F.lit(1.5) + F.substring("voter", 2, 1).cast("int")).cast("decimal(14,2)"))
        g = mg.graph_of(b)
        assert _rows(alike.widest_paths(b)) == _rows(g.named(whole(g, "blocked"), "a", "b").select("a", "b", "width"))
        assert asked.pop() * 3 <= g.vertices.count()
