"""Operators that SQL cannot express, beside plain versions of them."""

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefgraph.llm import decontam, learn, licenses, ngram_join, quality, sharding, suffix_dedup, topk, toxicity


def plain_report(rows, length):
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 by counting every window."""
    raws = [(i, (t or "").encode()) for i, t in rows]
    seen = Counter(raw[p : p + length] for _, raw in raws for p in range(len(raw) - length + 1))
    out = []
    for i, raw in raws:
        gone = bytearray(len(raw))
        for p in range(len(raw) - length + 1):
            if seen[raw[p : p + length]] > 1:
                gone[p : p + length] = b"\1" * length
        spans = sum(1 for k, x in enumerate(gone) if x and (k == 0 or not gone[k - 1]))
        out.append((i, len(raw), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(raw, gone, strict=True) if not g)).hexdigest()))
    return sorted(out, key=str)


def repeats(seed):
    """Texts of one, two and many letters, with shared passages, whole copies, texts in themselves periodic, nulls, and one long text."""
    r = random.Random(seed)
    line = lambda n, letters: "".join(r.choices(letters, k=n))
    shared = [line(r.randint(20, 90), "abcdé ") for _ in range(4)]
    texts = [None, "", "a" * 23, "a" * 200, "ab" * 60, line(300, "ab"), shared[0], shared[0], *[line(r.randint(0, 60), "abcdefgh日") + r.choice(shared) + line(r.randint(0, 60), "abcdefgh") for _ in range(30)]]
    texts.append(line(9000, "abcdefgh") + shared[1] + line(3000, "abcdefgh") + shared[1][3:])
    return list(enumerate(texts)) + [(None, shared[2]), (3, "a" * 200)]


@pytest.mark.parametrize(("seed", "hot"), [(1, suffix_dedup.HOT), (2, 2)])
def test_repeated_substrings(spark, seed, hot):
    rows = repeats(seed)
    docs = spark.createDataFrame([(i, t, 1, "x") for i, t in rows], "doc_id long, text string, fp long, key string")
    got = suffix_dedup.report(docs, 24, 8, hot)
    assert sorted((tuple(r) for r in got.collect()), key=str) == plain_report(rows, 24)


def test_toxicity_scores(spark):
    """A score is the logistic function of the bias and the weights of a text's distinct n-grams; null and empty texts have the bias only."""
    texts = ["You are BAD, bad, bad", "a fine day é日本", "", None, "xy", "bad " * 3000]
    model = toxicity.Model(np.random.default_rng(1).normal(size=toxicity.DIMS).astype(np.float32) / 50, -0.3)

    def slot(gram):
        packed = int.from_bytes(gram, "big")
        return ((packed * 0x9E3779B97F4A7C15 % 2**64 ^ len(gram)) * 0xC2B2AE3D27D4EB4F % 2**64) >> (64 - toxicity.BITS)

    def plain(text):
        low = bytes(b + 32 if 65 <= b <= 90 else b for b in (text or "").encode())
        slots = {slot(low[i : i + n]) for n in toxicity.LENGTHS for i in range(len(low) - n + 1)}
        return 1 / (1 + math.exp(-(model.bias + sum(float(model.weights[s]) for s in slots))))

    got = toxicity.with_score(spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string"), model).collect()
    assert all(abs(r.score - plain(r.text)) < 1e-6 for r in got) and len(got) == 6


def test_toxicity_ratio_and_sample(spark):
    """Features that one class alone has are weighed towards it; the sample keeps to its bounds and the true shares are the prior."""
    docs = spark.createDataFrame([(i, ("awful words " if i % 3 == 0 else "kind words ") + str(i) + " pad" * (i % 5)) for i in range(120)], "doc_id long, text string")
    labels = docs.select("doc_id", F.lit(1).alias("quality"), (F.col("doc_id") % 3 == 0).cast("int").alias("toxic"))
    sample, counts = learn.labelled_sample(docs, labels, "toxic", lambda d: F.lit(True), 40, 400)
    rows = sample.collect()
    assert counts == {0: 80, 1: 40} and 2 <= len(rows) < 40 and all(sum(len(r.text) for r in rows if r.y == y) <= 200 for y in (0, 1))
    one = toxicity.score_documents(docs, labels).collect()
    assert all(r.predicted == int(r.doc_id % 3 == 0) for r in one)


def test_quality_scores(spark):
    """A raw score adds one weight a feature, by the feature's bin; features are shares and counts of a text's bytes."""
    x = quality.text_features(__import__("pyarrow").array(["Ab 1,  b\n", None, "é!"]))
    assert x.shape[0] == 3 and x[0][0] == math.log1p(9) and abs(x[0][1] - 1 / 9) < 1e-12 and abs(x[0][2] - 2 / 9) < 1e-12 and abs(x[0][3] - 1 / 9) < 1e-12 and x[1][0] == 0
    rng = np.random.default_rng(5)
    rows, y = rng.normal(size=(400, 3)), np.zeros(400, int)
    y[rows[:, 1] > 0.2] = 1
    ranker = quality.fit(rows, y, {0: int((y == 0).sum()), 1: int((y == 1).sum())})
    plain = [sum(ranker.weights[k][sum(c <= r[k] for c in ranker.cuts[k])] for k in range(3)) for r in rows]
    assert np.allclose(ranker.raw(rows), plain)
    score = ranker.score(rows)
    assert np.mean((score >= quality.THRESHOLD) == (y == 1)) > 0.97 and min(plain[i] for i in np.flatnonzero(y)) > np.median([plain[i] for i in np.flatnonzero(y == 0)])


def test_sharding_places(spark):
    rows = [(i, None if i % 7 == 0 else "té" * i) for i in range(300)]
    got = {r.doc_id: r for r in sharding.shard_documents(spark.createDataFrame(rows, "doc_id long, text string"), 7).collect()}
    for i, t in rows:
        raw, place = (t or "").encode(), sharding.place(i, 300, 7)
        assert (got[i].size, got[i].text_crc32, got[i].shard, got[i].slot) == (len(raw) + 16, zlib.crc32(raw), *place) and sharding.row_at(*place, 300, 7) == i


def test_licences_by_text_and_by_digest(spark, tmp_path):
    mit, word = licenses.KNOWN["MIT"], "A licence of its own,\nfor ANY organisation.\n"
    (tmp_path / "Own-1.0.txt").write_text(word)
    texts = [
        "The MIT License (MIT)\n\nCopyright (c) 2020 A. Person\n\n" + mit, mit.upper().replace(" ", "\n"), "Copyright The Some Authors\n" + licenses.KNOWN["BSD-3-Clause"], "Copyright: 2020 X\nISC License\n" + licenses.KNOWN["ISC"],
        mit + " and more", "# Copyright 2021\n# a LICENSE of its own for any organization", None, "",
    ]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert [r.license_id for r in licenses.scan_documents(docs).orderBy("doc_id").collect()] == ["MIT", "MIT", "BSD-3-Clause", "ISC", None, None, None, None]
    own = licenses.read_texts(spark, str(tmp_path))
    assert [r.license_id for r in licenses.scan_documents(docs, own).orderBy("doc_id").collect()] == [None] * 5 + ["Own-1.0", None, None]
    assert {"Apache-2.0", "MPL-2.0", "GPL-3.0", "LGPL-2.1", "CC0-1.0"} <= set(licenses.DIGESTS) and all(len(d) == 64 for d in licenses.DIGESTS.values())


def test_spans_leave_the_raw_text(spark):
    leak = "One two three four five six seven eight nine ten"
    docs = spark.createDataFrame([(1, f"Keep THIS, please: {leak.upper()}! And (that)."), (2, "Clean -- Text"), (3, None), (4, leak)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, leak)], "item_id long, text string")
    got = {r.doc_id: r.text for r in decontam.remove_spans(docs, bench).collect()}
    assert got == {1: "Keep THIS, please: And (that).", 2: "Clean -- Text", 3: None, 4: ""}


def test_join_with_clashing_columns(spark):
    names = ["_id", "a", "b", "c", "c1", "c2", "node", "root", "v", "n", "t1", "kind", "component_id", "many"]
    text = " ".join(f"w{i}" for i in range(30))
    rows = [(1, text, *range(14)), (2, text + " end", *range(14)), (3, "else " * 7, *range(14))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, " + ", ".join(f"{n} int" for n in names))
    assert {r.doc_id: r.component_id for r in ngram_join.similar_documents(docs).collect()} == {1: 1, 2: 1, 3: 3}


def test_floors_skip_but_lose_nothing(spark):
    rng = np.random.default_rng(9)
    x = rng.integers(-40, 40, size=(300, 6)).astype(np.float64)
    ids, queries = np.arange(300), np.arange(0, 300, 10)
    pivots = topk.choose_pivots({6: (ids, x)}, 8)[6]
    d = np.sqrt(((x[:, None, :] - pivots[None]) ** 2).sum(axis=2))
    all_, done = topk.search_block(queries, x[queries], d[queries], ids, x, d, 5)
    floor = np.array([sorted((x @ x[q])[ids != q])[-5] for q in queries])
    few, less = topk.search_block(queries, x[queries], d[queries], ids, x, d, 5, floor)
    assert few == all_ and less <= done
