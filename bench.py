"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

The graphs are charts of suppliers, charts of parts (the scale of the published ones where the tables are those of sf0.1), and, in
sessions of their own with fewer cores, the scaling over cores and the sequential closure beside the winners on one core.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from prefgraph.operators import ballots as bl
from prefgraph.operators import margins as mg
from prefgraph.operators import metrics, paths, rule
from prefgraph.plans import winners as wn
from prefgraph.plans.storage import store

SETS = {"europe15": (15, "EUROPE"), "europe20": (20, "EUROPE"), "global15": (15, None), "global20": (20, None)}
PARTS = ("europe20", "global20")
BUDGET = 240  # seconds after which the sessions with fewer cores are left out


def session(cpus: int) -> SparkSession:
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def graph(spark: SparkSession, sf: str, name: str, alt: str):
    k, region = SETS[name]
    return mg.graph_of(store(bl.chart_ballots(spark, sf, region=region, k=k, alt=alt), "ballots"))


def won(g) -> tuple[wn.WinnersResult, list]:
    found = wn.find_winners(g)
    return found, sorted(r.alt for r in g.vertices.join(found.winners, "id", "left_semi").collect())


def few_cores(cpus: int, sf: str, both: bool) -> dict:
    """Seconds of the winners (and of the sequential closure's ranking) on charts of suppliers, all nations; a small graph warms up."""
    spark = session(cpus)
    won(graph(spark, sf.replace("sf0.1", "sf0.001"), "global20", "l_suppkey"))
    g = graph(spark, sf, "global20", "l_suppkey")
    if not both:
        return {"seconds": metrics.timed_run(lambda: won(g))[0]}
    return metrics.compare(lambda: won(g), lambda: rule.ranking(paths.all_pairs_widest(g, "fw"), g.vertices).collect())


def child(cpus: int, sf: str, both: bool) -> dict | None:
    try:
        done = subprocess.run([sys.executable, __file__, "--few", str(cpus), sf, str(int(both))], capture_output=True, text=True, check=True, timeout=150)
    except (subprocess.TimeoutExpired, subprocess.CalledProcessError):
        return None
    return json.loads(done.stdout.strip().splitlines()[-1])


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "8"))
    start, spark = time.time(), session(cpus)
    won(graph(spark, sf.replace("sf0.1", "sf0.001"), "global20", "l_suppkey"))  # compiles the plans
    seconds: dict[str, float] = {}
    shape: dict[str, dict] = {}
    for name, alt in [*((n, "l_suppkey") for n in SETS), *((n, "l_partkey") for n in PARTS)]:
        label = name if alt == "l_suppkey" else f"{name}_parts"
        began = time.time()
        g = graph(spark, sf, name, alt)
        seconds[f"graph_{label}"] = round(time.time() - began, 2)
        began = time.time()
        found, winners = won(g)
        seconds[f"winners_{label}"] = round(time.time() - began, 2)
        edges = g.edges.told["n"]
        shape[label] = {"alternatives": g.vertices.count(), "edges": edges, "undecided": found.log[0]["undecided"], "rounds": found.rounds, "supersteps": found.supersteps, "winners": winners, "core_seconds_a_million_edges": round(seconds[f"winners_{label}"] * cpus / edges * 1e6, 2)}
        if label == "global20":
            began = time.time()
            rule.ranking(paths.all_pairs_widest(g, "fw"), g.vertices).collect()
            seconds["sequential_ranking_global20"] = round(time.time() - began, 2)
    spark.stop()
    more: dict = {}
    if time.time() - start < BUDGET and (one := child(1, sf, True)):
        more["one_core_against_closure_global20"] = one
        others = {c: x["seconds"] for c in (2, 4) if time.time() - start < BUDGET and (x := child(c, sf, False))}
        more["scaling_global20"] = metrics.scaling({1: one["seconds"], **others}.__getitem__, [1, *others])
    headline = round(sum(v for k, v in seconds.items() if k.startswith("winners_") and not k.endswith("_parts")), 2)
    print(json.dumps({"metric": "winner determination on four chart graphs", "value": headline, "unit": "sec", "queries": seconds, "sf": os.path.basename(sf.rstrip("/")), "cpus": cpus, "graphs": shape, **more}))


if __name__ == "__main__":
    if sys.argv[1:2] == ["--few"]:
        print(json.dumps(few_cores(int(sys.argv[2]), sys.argv[3], sys.argv[4] == "1")))
    else:
        main()
