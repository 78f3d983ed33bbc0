"""Top-k with finite components of any size, beside brute force in Python integers."""

import math
import random

import pytest
from pyspark.sql import functions as F

from prefgraph.llm import topk


def test_far_vectors_take_part(spark):
    r = random.Random(12)
    rows = [(i, [r.uniform(-1, 1) for _ in range(4)]) for i in range(60)]
    rows += [(60, [16384.0, 0.3, -0.2, 0.1]), (61, [-3e6, 0.77, 1e5, -0.01]), (62, [0.5, 40000.25, -40000.25, 1.0]), (100, [20000.5, -1.0, 0.1, 7.0]), (150, [1e9, 2e3, 1.0, -0.003]), (63, [1e22, 0.0, 0.0, 0.0]), (63, [-1e22, 1e22, 0.0, 0.0])]
    rows += [(50, [9e4, 0.0, 0.0, 0.0]), (64, [float("inf"), 0.0, 0.0, 0.0]), (65, [1e5, 2.0]), (200, [0.5, 1.0])]
    rows[0] = (0, [0.0, 0.0, 0.5, 0.5])
    dull = [x for x in rows if x[0] not in (63, 64)]
    got = {}
    for x in topk.top_k(spark.createDataFrame(dull, "vec_id long, embedding array<double>"), F.col("vec_id") % 50 == 0).collect():
        got.setdefault(x.query_id, []).append((x.rank, x.vec_id, x.score))
    fine = [(i, [math.floor(256 * x) for x in v]) for i, v in dull]
    asked = {}
    for i, v in fine:
        if i % 50 == 0:
            asked[i] = min(v, asked.get(i, v))
    assert got.keys() == asked.keys() == {0, 50, 100, 150, 200}
    for q, c in asked.items():
        best = sorted((-sum(a * b for a, b in zip(c, v, strict=True)), i) for i, v in fine if i != q and len(v) == len(c))[:5]
        assert sorted(got[q]) == [(k, i, -s) for k, (s, i) in enumerate(best, 1)]
    assert any(v >= 60 for v in (x[1] for x in got[0]))
    huge = spark.createDataFrame([(0, [0.0, 1.0]), (1, [1e22, 0.5]), (2, [-1e22, 0.25]), (50, [-2.0, 0.0])], "vec_id long, embedding array<double>")
    ask = lambda k, q: [(x.vec_id, x.score) for x in topk.top_k(huge, F.col("vec_id") == q, k).orderBy("rank").collect()]
    assert ask(3, 0) == [(1, 128 * 256), (2, 64 * 256), (50, 0)]
    with pytest.raises(Exception, match="no long"):
        ask(1, 50)
