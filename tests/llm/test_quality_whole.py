"""op7 learns from every labelled document of its folds, not from the first thousands."""

import zlib

import numpy as np

from prefgraph.llm import quality


def test_all_labels_take_part(spark):
    """9,000 labels: the share at the threshold is that of all of them, and pairs in blocks add up to their gradient."""
    rows = [(i, "Fine words, all in order. " * (1 + i % 5) if i % 3 else "zz 99 ## " * (1 + i % 7), int(i % 3 > 0)) for i in range(9000)]
    docs, labels = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string"), spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id long, quality int")
    seen = []
    nth = quality._nth
    quality._nth = lambda scores, *a: (seen.append(scores.count()), nth(scores, *a))[1]
    try:
        got = {r.doc_id: r.predicted for r in quality.score_documents(docs, labels).collect()}
    finally:
        quality._nth = nth
    used = sum(zlib.crc32(str(i).encode()) % 4 != 2 for i in range(9000))
    assert seen == [used, used] and used > 6000
    assert np.mean([got[i] == y for i, _, y in rows]) > 0.99


def test_sums_over_pairs():
    r = np.random.default_rng(2)
    good, bad = (r.integers(0, 10, (n, quality.WIDTH)).astype(np.uint8) + np.arange(0, 180, 10, dtype=np.uint8) for n in (5, 3))
    v, e = r.normal(size=180), 1e-6
    loss, pairs, grad, hess = quality._sums(good, bad, v)
    want = sum(np.logaddexp(0, v[b].sum() - v[a].sum()) for a in good for b in bad)
    assert pairs == 15 and abs(loss - want) < 1e-9
    for k in (0, 17, 93):
        d = np.zeros(180)
        d[k] = e
        up, down = quality._sums(good, bad, v + d), quality._sums(good, bad, v - d)
        assert abs((up[0] - down[0]) / (2 * e) - grad[k]) < 1e-4 and np.allclose((up[2] - down[2]) / (2 * e), hess[k], atol=1e-4)
