"""Graphs and profiles that one task decides, beside brute force; alternatives that all voters rank alike are one class."""

import itertools
import random

import numpy as np
import pytest

from prefgraph.operators import onetask, rankedpairs
from prefgraph.operators.graph import from_edges
from prefgraph.plans import alike, winners
from test_whole_tables import margins_of, undefeated, widest


def _profile(r, clones):
    """(voters as maps of an alternative to its score, ballots rows): alternatives a have clones a + 100, a + 200, ... of the same scores."""
    voters = []
    for _ in range(r.randint(3, 7)):
        own = {a: r.randint(1, 4) for a in r.sample(range(7), r.randint(2, 7))}
        voters.append({a + 100 * k: x for a, x in own.items() for k in range(clones)})
    rows = [(f"v{i}", a, 1 + sum(y > x for y in v.values()), 1) for i, v in enumerate(voters) for a, x in v.items()]
    return voters, rows


def _parts(spark, seed, clones=3):
    voters, rows = _profile(random.Random(seed), clones)
    alts = sorted({a for v in voters for a in v})
    return alts, margins_of(voters, alts, True), spark.createDataFrame(rows, "voter string, alt long, rank int, weight long")


def _got(df):
    return sorted(r.alt for r in df.collect())


@pytest.mark.parametrize("matrix", [alike.MATRIX, 0])
def test_winners_of_classes(spark, monkeypatch, matrix):
    monkeypatch.setattr(alike.Alike.held, "__defaults__", (matrix,))
    for seed in (1, 2):
        alts, w, b = _parts(spark, seed)
        assert alike.Alike(b).m * 3 <= len(alts)
        assert _got(alike.winners(b)) == sorted(undefeated(alts, w))


def test_undefeated_beside_brute_force():
    r = random.Random(4)
    for k in range(150):
        n, low = r.randint(1, 9), r.choice([0.2, 0.6, 1])
        edges = [(a, b, r.randint(1, 1 + k % 6)) for a, b in itertools.permutations(range(n), 2) if a < b and r.random() < low]
        edges = [e if r.random() < 0.5 else (e[1], e[0], e[2]) for e in edges]
        want = sorted(undefeated(range(n), {(a, b): w for a, b, w in edges}))
        src, dst, w = (np.array([e[i] for e in edges], np.int32) for i in range(3))
        m = np.zeros((n, n), np.int16)
        m[src, dst], m[dst, src] = w, -w
        assert onetask.undefeated(onetask.Dense(m)).tolist() == want == onetask.undefeated(onetask.Sparse(n, src, dst, w)).tolist()


def _reached(alts, w):
    return widest(alts, w)


def test_schwartz_set_of_classes(spark):
    for seed in (3, 5):
        alts, w, b = _parts(spark, seed)
        p = _reached(alts, w)
        assert _got(alike.schwartz_set(b)) == [a for a in alts if all((a, x) in p for x in alts if (x, a) in p)]


def test_uncovered_set_of_classes(spark):
    for seed in (6, 7):
        alts, w, b = _parts(spark, seed)
        covers = lambda x, a: (x, a) in w and all((x, c) in w for c in alts if (a, c) in w)  # noqa: B023, E731
        assert _got(alike.uncovered_set(b)) == [a for a in alts if not any(covers(x, a) for x in alts)]


@pytest.mark.parametrize("most", [alike.CLOSURE, 0])
def test_ranking_of_classes(spark, monkeypatch, most):
    monkeypatch.setattr(alike, "CLOSURE", most)
    alts, w, b = _parts(spark, 8)
    p = widest(alts, w)
    wins = lambda x, y: p.get((x, y), 0) > p.get((y, x), 0)
    beaten = {a: sum(wins(x, a) for x in alts) for a in alts}
    want = {(a, beaten[a], sum(wins(a, x) for x in alts), 1 + sum(beaten[x] < beaten[a] for x in alts)) for a in alts}
    assert {(r.alt, r.beaten_by, r.beats, r.rnk) for r in alike.ranking(b).collect()} == want


@pytest.mark.parametrize("most", [winners.ONE_TASK, 0])
def test_one_task_or_passes(spark, monkeypatch, most):
    """A sparse graph of 300 vertices with many ties: pivots do not halve it, one task decides it."""
    monkeypatch.setattr(winners, "ONE_TASK", most)
    r = random.Random(9)
    edges = {(a, b): r.randint(1, 2) for a, b in (r.sample(range(300), 2) for _ in range(500)) if a < b}
    g = from_edges(spark, [(a, b, w) for (a, b), w in edges.items()] + [(299, 400, 2)], list(range(300)))
    found = winners.find_winners(g)
    assert ("task" in {x["kind"] for x in found.log}) == (most > 0)
    edges[299, 400] = 2
    assert {x.id for x in found.winners.collect()} == {v for v in [*range(300), 400] if not any(b == v for _, b in edges)}


def test_acyclic_subgraph_peels_to_its_cycles(spark, monkeypatch):
    """Layers of edges on no cycle around a cycle of three: the sequential task, which may hold three vertices here, gets the cycle only."""
    monkeypatch.setattr(rankedpairs, "LIMIT", 3)
    chain = [(10 + i, 11 + i) for i in range(6)] + [(16, 1), (3, 20)] + [(20 + i, 21 + i) for i in range(5)]
    edges = [(1, 2), (2, 3), *chain, (3, 1)]
    rows = rankedpairs.emas(spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(edges)], "ord long, src long, dst long")).collect()
    assert sorted((r.src, r.dst) for r in rows) == sorted(edges) and [(r.src, r.dst) for r in rows if not r.kept] == [(3, 1)]


def test_profile_beside_its_matrix():
    """Margins that are worked out when they are asked for give what the matrix of all of them gives."""
    r = np.random.default_rng(5)
    for k in range(60):
        n, voters = int(r.integers(2, 12)), int(r.integers(1, 9))
        ranks = r.integers(0, int(r.integers(1, n + 1)), (voters, n))
        weight = r.integers(1, 4, voters) if k % 2 else np.ones(voters, np.int64)
        p = onetask.Profile(onetask.dense_ranks(ranks), weight)
        m = onetask.margin_matrix(p)
        assert (m == sum(x * np.sign(q[None] - q[:, None]) for q, x in zip(ranks, weight, strict=True))).all()
        edges = {(int(a), int(b)): int(m[a, b]) for a, b in np.argwhere(m > 0)}
        assert onetask.undefeated(p).tolist() == sorted(undefeated(range(n), edges))
        assert sorted(np.concatenate(onetask.sources(p))) == sorted(np.concatenate(onetask.sources(onetask.Dense(m))))
        assert onetask.uncovered_of(p, np.arange(n), sample=3).tolist() == onetask.uncovered(m).tolist()


def test_one_task_takes_more_alternatives_than_a_matrix(spark):
    """13,000 alternatives of which no two are alike, by two voters that agree: the first wins."""
    n = 13_000
    rows = spark.range(n).selectExpr("explode(array('x', 'y')) as voter", "id as alt", "cast(id + 1 as int) as rank", "cast(1 as long) as weight")
    b = alike.Alike(rows)
    assert b.m == n and b.held()
    assert _got(alike.winners(rows)) == [0] == _got(alike.schwartz_set(rows))


def test_uncovered_set_in_several_tasks(spark, monkeypatch):
    monkeypatch.setattr(alike, "WHOLE", 0)
    for seed in (6, 7):
        alts, w, b = _parts(spark, seed)
        covers = lambda x, a: (x, a) in w and all((x, c) in w for c in alts if (a, c) in w)  # noqa: B023, E731
        assert _got(alike.uncovered_set(b)) == [a for a in alts if not any(covers(x, a) for x in alts)]
