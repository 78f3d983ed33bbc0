"""Registered queries on small tables of their own, beside brute force over every row."""

import itertools
import random

from prefgraph.operators import margins
from prefgraph.queries import QUERIES


def widest(vertices, w):
    """Max-min closure of the weights w[a, b]; pairs without a path are missing."""
    w = dict(w)
    for k, a, b in itertools.product(vertices, repeat=3):
        if a != b and (x := min(w.get((a, k), 0), w.get((k, b), 0))) > w.get((a, b), 0):
            w[a, b] = x
    return w


def undefeated(vertices, w):
    p = widest(vertices, w)
    return {v for v in vertices if not any(p.get((u, v), 0) > p.get((v, u), 0) for u in vertices)}


def margins_of(ballots, vertices, unlisted_last):
    """Positive margins; ballots are maps of an alternative to its score, the highest first."""
    low = float("-inf")
    out = {}
    for a, b in itertools.permutations(vertices, 2):
        m = 0
        for x in ballots:
            if unlisted_last or (a in x and b in x):
                m += (x.get(a, low) > x.get(b, low)) - (x.get(a, low) < x.get(b, low))
        if m > 0:
            out[a, b] = m
    return out


def test_head_to_head_takes_every_order(spark, tmp_path):
    r = random.Random(5)
    orders = {o: {a: r.randint(1, 9) for a in r.sample(range(6), r.randint(1, 4))} for o in range(1, 45)}
    rows = [(o, a, float(q)) for o, x in orders.items() for a, q in x.items()]
    spark.createDataFrame(rows, "l_orderkey long, l_suppkey long, l_quantity double").selectExpr("*", "l_suppkey as l_partkey").write.parquet(f"{tmp_path}/lineitem.parquet")
    alts = {a for x in orders.values() for a in x}
    for name in ("winners_headtohead_supplier", "winners_headtohead_part"):
        got = {x.alt for x in QUERIES[name](spark, str(tmp_path)).collect()}
        assert got == undefeated(alts, margins_of(orders.values(), alts, unlisted_last=False))


def test_embeddings_take_every_vector(spark, tmp_path):
    r = random.Random(3)
    vectors = {i: [r.random() for _ in range(5)] for i in (1, 2, 199, 200, 201, 350)}
    vectors[350] = [2.0, 2.0, 2.0, *vectors[350][3:]]
    spark.createDataFrame(list(vectors.items()), "vec_id long, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    rows = QUERIES["ballots_embeddings"](spark, str(tmp_path)).collect()
    assert {(x.voter, x.alt, x.rank) for x in rows} == {(str(d), i, 1 + sum(w[d] > v[d] for w in vectors.values())) for d in range(5) for i, v in vectors.items()}
    voters = [{i: v[d] for i, v in vectors.items()} for d in range(5)]
    got = {x.alt for x in QUERIES["winners_embeddings"](spark, str(tmp_path)).collect()}
    assert got == undefeated(vectors, margins_of(voters, vectors, unlisted_last=True)) == {350}


def _lineitem(spark, path, edges):
    spark.createDataFrame([(7 * i + 1, a, b) for i, (a, b) in enumerate(edges)], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{path}/lineitem.parquet")
    return str(path)


def reached_from(a, edges):
    seen, todo = {a}, [a]
    while todo:
        v = todo.pop()
        for x, y in edges:
            if x == v and y not in seen:
                seen.add(y)
                todo.append(y)
    return seen


def test_acyclic_subgraph_takes_every_edge(spark, tmp_path):
    r = random.Random(8)
    edges = {(r.randrange(90), r.randrange(45)) for _ in range(160)} - {(i, i) for i in range(90)}
    rows = sorted(QUERIES["acyclic_subgraph"](spark, _lineitem(spark, tmp_path, edges)).collect(), key=lambda x: x.ord)
    assert {(x.src, x.dst) for x in rows} == edges and len(rows) == len(edges)
    kept = []
    for x in rows:
        assert x.kept == (x.src not in reached_from(x.dst, kept))
        if x.kept:
            kept.append((x.src, x.dst))
    assert len(kept) < len(rows)


def test_reachability_takes_every_edge(spark, tmp_path):
    for name, edges, want in (("yes", [(0, 40), (40, 25), (25, 13), (25, 40), (99, 0)], True), ("no", [(0, 40), (40, 33), (99, 13)], False)):
        got = QUERIES["reduction_reachability"](spark, _lineitem(spark, tmp_path / name, edges)).collect()
        assert [tuple(x) for x in got] == [(want, want)]


def test_margins_by_group_count_appearances(spark):
    r = random.Random(6)
    ballots = [(f"v{i}", "NS"[i % 2], i % 3 + 1, {a: r.randint(1, 3) for a in r.sample(range(6 if i % 2 else 4), 2)}) for i in range(9)]
    rows = [(v, g, a, k, w) for v, g, w, x in ballots for a, k in x.items()]
    b = spark.createDataFrame(rows, "voter string, region string, alt long, rank int, weight long")
    for unlisted, absent in (("last", 99), ("ignore", None)):
        want = {}
        for level in ("N", "S", None):
            voters = [(w, x) for _, g, w, x in ballots if level in (g, None)]
            for p, q in itertools.combinations(sorted({a for _, x in voters for a in x}), 2):
                both = [(w, x.get(p, absent), x.get(q, absent)) for w, x in voters if absent or (p in x and q in x)]
                if both:
                    want[level, p, q] = sum(w * ((i < j) - (i > j)) for w, i, j in both)
        got = margins.by_group(b, "region", unlisted).collect()
        assert {(x.region, x.a, x.b): x.margin for x in got} == want and len(got) == len(want)
    total = {(x.a, x.b): x.margin for x in margins.by_group(b, "region").collect() if x.region is None}
    assert total == {(x.a, x.b): x.margin for x in margins.majority_margins(b).collect() if x.a < x.b}
