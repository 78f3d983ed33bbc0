"""Shapes of graphs, run times and logs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import PrefGraph


def graph_stats(g: PrefGraph) -> DataFrame:
    """(alternatives, edges, max_weight, density): density is of unordered pairs."""
    m = g.vertices.agg(F.count(F.lit(1)).alias("alternatives"))
    e = g.edges.agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.max("w"), F.lit(0)).alias("max_weight"))
    pairs = F.col("alternatives") * (F.col("alternatives") - 1) / 2
    return m.join(e, F.lit(True)).withColumn("density", F.when(pairs > 0, F.round(F.col("edges") / pairs, 6)))


def vertex_stats(g: PrefGraph) -> DataFrame:
    """(id, out_degree, in_degree, max_out, max_in), 0 where there are no edges."""
    out = g.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("out_degree"), F.max("w").alias("max_out"))
    into = g.edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("in_degree"), F.max("w").alias("max_in"))
    return g.vertices.select("id").join(out, "id", "left").join(into, "id", "left").na.fill(0, ["out_degree", "in_degree", "max_out", "max_in"]).select("id", "out_degree", "in_degree", "max_out", "max_in")


def weight_histogram(g: PrefGraph) -> DataFrame:
    return g.edges.groupBy("w").agg(F.count(F.lit(1)).alias("n"))


def timed_run(call: Callable, repeats: int = 1) -> tuple[float, object]:
    """The least seconds of some runs and the last result."""
    best, out = float("inf"), None
    for _ in range(repeats):
        began = time.time()
        out = call()
        best = min(best, time.time() - began)
    return best, out


def scaling(run: Callable[[int], float], cores: list[int]) -> list[dict]:
    """Seconds of run(cores), speed-up over the least number of cores and efficiency, for each number of cores."""
    seconds = {c: run(c) for c in sorted(cores)}
    least = min(seconds)
    return [{"cores": c, "seconds": round(s, 2), "speed_up": round(seconds[least] / s, 2), "efficiency": round(seconds[least] * least / (s * c), 2)} for c, s in seconds.items()]


def compare(ours: Callable[[], object], baseline: Callable[[], object]) -> dict:
    """Seconds of both and how many times ours the baseline takes."""
    one, two = timed_run(ours)[0], timed_run(baseline)[0]
    return {"seconds": round(one, 2), "baseline_seconds": round(two, 2), "ratio": round(two / one, 2)}


def plan_text(df: DataFrame) -> str:
    import contextlib
    import io

    with contextlib.redirect_stdout(held := io.StringIO()):
        df.explain("formatted")
    return held.getvalue()
