"""The worked example, brute force on random graphs, literal counterexamples and the constructions."""

import itertools
import random

import pytest

from prefgraph.operators import ballots, checks, components, margins, paths, rankedpairs, reductions, rule, scores, synth
from prefgraph.operators.graph import from_edges
from prefgraph.plans import winners

A, B, C, D = 1, 2, 3, 4
EXAMPLE = [(A, B, 4), (A, C, 6), (B, C, 10), (C, D, 8), (D, A, 2), (D, B, 12)]
WIDTHS = {(A, B): 6, (A, C): 6, (A, D): 6, (B, A): 2, (B, C): 10, (B, D): 8, (C, A): 2, (C, B): 8, (C, D): 8, (D, A): 2, (D, B): 12, (D, C): 10}


def ids(df):
    return {r.id for r in df.collect()}


def brute(vertices, edges):
    w = {(a, b): 0 for a in vertices for b in vertices}
    w.update({(a, b): x for a, b, x in edges})
    for k, a, b in itertools.product(vertices, repeat=3):
        w[a, b] = max(w[a, b], min(w[a, k], w[k, b]))
    return {v for v in vertices if not any(u != v and w[u, v] > w[v, u] for u in vertices)}


@pytest.fixture(scope="module")
def example(spark):
    return from_edges(spark, EXAMPLE)


@pytest.mark.parametrize("method", ["fw", "squaring", "blocked", "vertex"])
def test_widths(example, method):
    assert {(r.a, r.b): r.width for r in paths.all_pairs_widest(example, method).collect()} == WIDTHS


def test_example_rules(spark, example):
    p = paths.all_pairs_widest(example, "fw")
    assert ids(rule.winners_exact(p, example.vertices)) == {A}
    assert {r.id: r.rnk for r in rule.ranking(p, example.vertices).collect()}[A] == 1
    assert ids(components.schwartz_set(example)) == {A, B, C, D}
    assert rule.is_winner(example, A)[0] and not rule.is_winner(example, D)[0] and rule.is_unique_winner(example, A)
    assert paths.widest_by_threshold(example, D, C) == 10 and paths.widest_path(example, D, C) == [D, B, C] and paths.path_width(spark, [D, B, C], example) == 10
    assert paths.path_width(spark, [B, A], example) is None and not paths.wide_path_exists(example, B, A, 2, strict=True) and components.reachable(example, B, A)
    m = spark.createDataFrame([(a, b, w) for a, b, w in EXAMPLE] + [(b, a, -w) for a, b, w in EXAMPLE] + [(x, y, 0) for x, y in []], "a long, b long, margin long")
    order = spark.createDataFrame([(A, 4), (B, 2), (C, 1), (D, 3)], "alt long, pos int")
    assert {(r.a, r.b) for r in rankedpairs.kept_pairs(m, order).filter("kept").collect()} == {(D, B), (B, C), (A, C), (A, B), (D, A)}
    assert rankedpairs.is_winner(m, order, D)


def test_literals(spark):
    tied = from_edges(spark, [(0, 2, 6), (1, 0, 6), (1, 2, 2), (2, 3, 4), (3, 0, 4), (3, 1, 4)])
    assert ids(winners.find_winners(tied).winners) == {1, 3}
    peel = from_edges(spark, [(0, 1, 14), (1, 3, 38), (2, 0, 20), (2, 1, 36), (3, 0, 6), (3, 2, 22)])
    order = lambda df: [r.id for r in df.orderBy("tier").collect()]
    assert order(rule.top_k(peel, 4)) == [2, 0, 1, 3] and order(rule.top_k(peel, 4, "ranking")) == [2, 1, 3, 0]
    alone = from_edges(spark, [(1, 2, 1)], [1, 2, 3]).at_least(2)
    assert ids(winners.find_winners(alone).winners) == {1, 2, 3} == ids(winners.find_winners(alone, "labels", finish_threshold=0).winners)
    cycles = from_edges(spark, [(1, 2, 2), (2, 3, 2), (3, 1, 2), (4, 5, 2), (5, 6, 2), (6, 4, 2)])
    assert ids(components.schwartz_set(cycles)) == {1, 2, 3, 4, 5, 6} and {(r.id, r.scc) for r in components.strongly_connected(cycles).collect()} == {(1, 1), (2, 1), (3, 1), (4, 4), (5, 4), (6, 4)}


@pytest.mark.parametrize("flags", [{"strategy": "labels", "finish_threshold": 0, "prune": "zero"}, {"strategy": "labels", "finish_threshold": 0, "combiner": False, "init": False}, {"strategy": "labels", "finish_threshold": 0, "labels": 3, "init": False}, {"strategy": "labels", "finish_threshold": 0, "labels": 2, "ids": "borda_asc", "prune": "none"}, {"strategy": "pivot", "ids": "key"}, {"finish_threshold": 0}, {}])
def test_strategies(spark, flags):
    """Several random graphs side by side are one graph; its winners are theirs."""
    r = random.Random(str(sorted(flags)))
    edges, want, vertices = [], set(), []
    for k in range(6):
        own = list(range(10 * k, 10 * k + r.randint(1, 7)))
        mine = [(a, b, r.choice([2, 4, 6])) if r.random() < 0.5 else (b, a, r.choice([2, 4, 6])) for a, b in itertools.combinations(own, 2) if r.random() < r.choice([0.4, 0.7, 1])]
        edges, want, vertices = edges + mine, want | brute(own, mine), vertices + own
    g = from_edges(spark, edges, vertices)
    found = winners.find_winners(g, **flags)
    assert ids(found.winners) == want and found.log[0]["kind"] == "init"
    if not flags:
        assert ids(winners.via_schwartz(g)) == want


def test_margins_by_hand(spark):
    rows = [("x", 1, 1), ("x", 2, 2), ("y", 2, 1), ("y", 3, 1), ("z", 3, 1)]
    b = spark.createDataFrame([(v, a, r, 1) for v, a, r in rows], "voter string, alt long, rank int, weight long")
    lists = {v: {a: r for w, a, r in rows if w == v} for v, _, _ in rows}
    place = lambda v, a: lists[v].get(a, 99)
    prefer = {(a, c): sum(place(v, a) < place(v, c) for v in lists) for a in (1, 2, 3) for c in (1, 2, 3) if a != c}
    assert {(r.a, r.b): r.prefer for r in margins.pairwise_counts(b).collect()} == {k: v for k, v in prefer.items() if v}
    assert {(r.a, r.b): r.margin for r in margins.majority_margins(b).collect()} == {k: v - prefer[k[1], k[0]] for k, v in prefer.items()}
    assert sorted(map(tuple, ballots.unnest(ballots.nest(b)).select("voter", "alt", "rank").collect())) == sorted(rows)
    assert ballots.validate(b).isEmpty() and ballots.validate(b.unionByName(b)).count() == 5
    g = margins.graph_of(b)
    assert scores.condorcet_winner(g).count() == 0
    assert sorted(r.id for r in g.vertices.collect()) == [1, 2, 3]


def test_constructions(spark):
    r = random.Random(9)
    for _ in range(2):
        v = list(range(5))
        e = [(a, b) for a in v for b in v if a != b and r.random() < 0.3]
        reach, seen = {0}, None
        while reach != seen:
            seen = set(reach)
            reach |= {b for a, b in e if a in seen}
        g = reductions.reachability_to_wpr(spark.createDataFrame(e, "src long, dst long"), spark.createDataFrame([(i,) for i in v], "id long"), 0, 4)
        assert rule.is_winner(g, 0)[0] == rule.is_unique_winner(g, 0) == (4 in reach)
    e = [(1, 1, 2), (2, 2, 3), (3, 3, 1), (4, 1, 4)]
    edges = spark.createDataFrame(e, "ord long, src long, dst long")
    kept = {x.ord for x in rankedpairs.emas(edges).filter("kept").collect()}
    assert kept == {1, 2, 4}
    for f in (3, 2):
        assert rankedpairs.is_winner(*reductions.emas_to_ranked_pairs(edges, f), 0) == (f not in kept)
    small = from_edges(spark, [(1, 2, 2), (2, 3, 4), (3, 1, 2)])
    back = margins.majority_margins(reductions.realise_profile(small)).filter("margin > 0")
    assert {(x.a, x.b, x.margin) for x in back.collect()} == {(1, 2, 2), (2, 3, 4), (3, 1, 2)}


def test_axioms_and_synthetic(spark):
    b = synth.mallows(spark, 4, 15, 0.6)

    def won(profile):
        g = margins.graph_of(profile)
        return {r.alt for r in g.vertices.join(winners.find_winners(g).winners, "id").collect()}

    first = won(b)
    top = min(first)
    assert top in won(checks.raise_alternative(b, top))
    assert first - {top} == won(checks.clone(b, top, 99)) - {top, 99}
    g = synth.sparse_wmg(spark, 60, 0.1)
    assert ids(winners.find_winners(g).winners) == brute(range(1, 61), [tuple(x) for x in g.edges.collect()])


def test_superstep_plan(spark, example):
    """Few changed rows are broadcast to edges that stay where they are; the minimum is a partial and a final hash aggregation."""
    from pyspark.sql import functions as F

    from prefgraph.functions import pack
    from prefgraph.operators.metrics import plan_text
    from prefgraph.plans.bsp import superstep
    from prefgraph.plans.storage import BROADCAST_ROWS, store

    now = store(winners.init_labels(winners.initial_status(example)).withColumn("moved", F.lit(True)), moved=F.count(F.lit(1)))
    edges = store(example.edges)
    parts = winners.two_way(edges), ["direction"], lambda v, w: pack(v, w), F.min, lambda new, old: new < old
    text = plan_text(superstep(now, *parts)[0].groupBy("direction", "id").agg(F.min("value")))
    assert text.count("HashAggregate") >= 2 and "SortAggregate" not in text and "CartesianProduct" not in text
    assert "BroadcastHashJoin" in text and "SortMergeJoin" not in text and "hashpartitioning(src" not in text
    now.told = {"moved": BROADCAST_ROWS + 1}
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    assert "SortMergeJoin" in plan_text(superstep(now, *parts)[0])
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_no_cartesian_products(spark, example):
    from prefgraph.operators.metrics import plan_text

    p = paths.all_pairs_widest(example)
    order = spark.createDataFrame([(1, 1), (2, 2), (3, 3), (4, 4)], "alt long, rnk long")
    edges = spark.createDataFrame([(1, 1, 2), (2, 2, 3)], "ord long, src long, dst long")
    for df in (rule.relation(p, example.vertices), checks.kendall(order, order), reductions.emas_to_ranked_pairs(edges, 1)[0]):
        text = plan_text(df)
        assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


@pytest.mark.parametrize("scale", [float("nan"), 1 << 32, 0.1])
def test_weights_of_any_size_and_type(spark, scale):
    """Only the order of weights matters: whole weights beyond 31 bits and real ones give the winners and widths of small ones."""
    if scale != scale:
        g = from_edges(spark, EXAMPLE)
        g.edges = g.edges.selectExpr("src", "dst", "cast(w as decimal(9, 2)) / 4 as w")
        scale = 0.25
    else:
        g = from_edges(spark, EXAMPLE)
        g.edges = spark.createDataFrame([(a, b, w * scale) for a, b, w in EXAMPLE], "src long, dst long, w " + ("long" if scale > 1 else "double"))
    for flags in ({"strategy": "labels", "finish_threshold": 0}, {"strategy": "pivot"}, {}):
        assert ids(winners.find_winners(g, **flags).winners) == {A}
    for method in ("fw", "squaring", "blocked", "vertex"):
        assert {(r.a, r.b): round(float(r.width) / scale, 6) for r in paths.all_pairs_widest(g, method).collect()} == WIDTHS


def test_blocks_of_a_closure(spark):
    """More than one block of vertices, with blocks that only paths fill."""
    rng = random.Random(3)
    edges = [(a, b, rng.randint(1, 9)) for a, b in {tuple(sorted(rng.sample(range(9), 2))) for _ in range(14)}]
    g = from_edges(spark, [(a, b, w) if rng.random() < 0.5 else (b, a, w) for a, b, w in edges], list(range(9)))
    want = {tuple(r) for r in paths.all_pairs_widest(g, "squaring").collect()}
    assert {tuple(r) for r in paths._blocked(g, 4).collect()} == want


def test_scratch_and_log(spark, example, tmp_path, monkeypatch):
    """A run leaves its statuses and no other table; the log counts what moves."""
    from prefgraph.plans import storage

    monkeypatch.setattr(storage, "shared_folder", lambda s: str(tmp_path))
    found = winners.find_winners(example, "labels", finish_threshold=0, messages=True)
    assert ids(found.winners) == {A} and [x.name.split("-")[0] for x in tmp_path.iterdir()] == ["status"]
    steps = found.log[1]["steps"]
    assert steps[0]["active"] == 2 * found.log[0]["undecided"] and steps[0]["messages"] > 0 and steps[-1]["changed"] == 0 and steps[0]["state_bytes"] > 0


def test_uncovered_set(spark, example):
    assert ids(components.uncovered_set(example)) == {A, C, D}
    rng = random.Random(11)
    for m in (4, 5, 7):
        edges = [(a, b, 2) if rng.random() < 0.5 else (b, a, 2) for a, b in itertools.combinations(range(m), 2) if rng.random() < 0.8]
        beats = {v: {b for a, b, _ in edges if a == v} for v in range(m)}
        expected = {v for v in range(m) if not any(v in beats[u] and beats[v] <= beats[u] for u in range(m))}
        assert ids(components.uncovered_set(from_edges(spark, edges, list(range(m))))) == expected
