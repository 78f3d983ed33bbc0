"""Components by brute force, in candidate groups of one task and in rounds."""

import random
import re

import pytest

from prefgraph.llm import ngram_join


def brute(rows):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]+", lambda m: m[0].lower(), t or ""))
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())

    sets = [shingles(t) for _, t in rows]
    comp = list(range(len(rows)))

    def find(i):
        while comp[i] != i:
            i = comp[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                comp[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[find(i)] = min(least.get(find(i), d), d)
    return {d: (len(sets[i]), least[find(i)]) for i, (d, _) in enumerate(rows)}


def corpus(seed):
    r = random.Random(seed)
    word = lambda: "".join(r.choice("abcdeé") for _ in range(r.randint(1, 4)))
    passage = [word() for _ in range(40)]
    rows = []
    for _ in range(40):
        base = [word() for _ in range(r.randint(1, 90))]
        if r.random() < 0.5:
            base += passage[: r.randint(10, 40)]
        for _ in range(r.choice([1, 1, 2, 5])):
            w = list(base)
            for _ in range(r.randint(0, 5)):
                if len(w) > 1:
                    w[r.randrange(len(w))] = word()
            rows.append(" ".join(w) if r.random() < 0.7 else "\n".join(w).upper().replace("É", "é"))
    rows += [None, "", " \n", "a b", "A B", "a b c", rows[0], rows[0]]
    r.shuffle(rows)
    return list(enumerate(rows))


@pytest.mark.parametrize(("seed", "large", "few"), [(1, 10**9, 16), (2, 10**9, 3), (3, 0, 16)])
def test_components(spark, monkeypatch, seed, large, few):
    monkeypatch.setattr(ngram_join, "FEW", few)
    rows = corpus(seed)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similar_documents(docs, large=large).collect()}
    assert got == brute(rows)


def test_one_of_each_and_null_ids(spark):
    rows = [(1, "a b c d e f g"), (2, "A b c d e f g"), (None, "a b c d e f g"), (None, None), (4, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumnRenamed("text", "text")
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in ngram_join.one_of_each(docs).collect()) == [(False, 1), (False, 4), (True, 0), (True, 0)]


def test_empty(spark):
    assert ngram_join.similar_documents(spark.createDataFrame([], "doc_id long, text string, n long, root string")).collect() == []


def test_large_groups_take_no_rounds(spark, monkeypatch):
    """Members that have much in common and are not linked: each met some pivots a round, and round followed round until all had been pivots."""
    r = random.Random(7)
    common = [f"c{i}" for i in range(60)]
    rows = [(i, " ".join(common[:40] + [f"w{r.randrange(10**9)}" for _ in range(24)])) for i in range(150)]
    rows += [(200 + i, t + " end") for i, (_, t) in enumerate(rows[:5])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    steps, plain = [], ngram_join.materialize
    monkeypatch.setattr(ngram_join, "materialize", lambda df, name: steps.append(name) or plain(df, name))
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in ngram_join.similar_documents(docs, large=2000).collect()}
    assert got == brute(rows)
    assert steps.count("links") <= 2


def test_one_meets_all_as_pairs_do():
    import numpy as np

    r = np.random.default_rng(3)
    orders = ngram_join.Orders(np.zeros(1 << 20, np.uint8))
    for _ in range(10):
        sets, pool = [], r.integers(0, 2**63, 300).astype(np.uint64)
        for k in range(60):
            base = sets[r.integers(k)] if k and r.random() < 0.5 else r.choice(pool, r.integers(2, 60))
            sets.append(np.unique(np.r_[base[r.random(len(base)) < 0.95], r.integers(0, 2**63, r.integers(1, 9)).astype(np.uint64)]))
        first = lambda label: [label.index(x) for x in label]
        assert first(ngram_join._Group(sets, orders)._many()) == first(ngram_join._Group(sets, orders)._few())


def test_a_sketch_of_more_counters(spark):
    assert [ngram_join.sketch_bits(n) for n in (0, 299_999, 300_000, 3_000_000, 10**9)] == [20, 20, 21, 24, 24]
    docs = spark.createDataFrame([(i, f"a b c d e f{i % 3}") for i in range(9)], "doc_id long, text string")
    for bits in (20, 22):
        levels = ngram_join.frequency_levels(docs, bits)
        assert len(levels) == 1 << bits
        assert sorted(levels[levels > 0].tolist()) == [2, 2, 2, 3]


def test_near_copies_make_few_pairs(spark, monkeypatch):
    """Ten near copies of each text: every two of them made a pair of each shingle bucket, however many shingles told the same."""
    r = random.Random(11)
    rows = []
    for i in range(25):
        base = [f"w{r.randrange(10**9)}" for _ in range(r.randint(60, 120))]
        for k in range(10):
            rows.append((100 * i + k, " ".join(base[: len(base) - r.randrange(3)] + [f"t{r.randrange(10**9)}" for _ in range(r.randrange(4))])))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    made, plain = {}, ngram_join.materialize
    monkeypatch.setattr(ngram_join, "materialize", lambda df, name: made.setdefault(name, plain(df, name)) if name == "shared" else plain(df, name))
    monkeypatch.setattr(ngram_join, "discard", lambda stored: None)
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in ngram_join.similar_documents(docs).collect()}
    assert got == brute(rows)
    assert made["shared"].count() < 25 * 45  # pairs of texts; there are 16 buckets


@pytest.mark.parametrize("above", [-99, 99])
def test_kins_of_all_sizes(spark, monkeypatch, above):
    """Whether kins are coarse or none are made, linked sets meet: here all least shingles are ones of a passage, and sizes of a kin vary by half."""
    monkeypatch.setattr(ngram_join, "ABOVE", above)
    monkeypatch.setattr(ngram_join, "SIZES", 1)
    r = random.Random(5)
    common = [f"c{i}" for i in range(30)]
    rows = []
    for i in range(60):
        base = common[: r.randint(8, 30)] + [f"w{r.randrange(10**9)}" for _ in range(r.randint(0, 60))]
        rows += [(10 * i + k, " ".join(base[k:] + [f"t{r.randrange(10**9)}"] * r.randrange(2))) for k in range(r.randint(1, 5))]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in ngram_join.similar_documents(docs).collect()}
    assert got == brute(rows)
