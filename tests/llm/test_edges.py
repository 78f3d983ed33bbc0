"""Each operator on nulls, empty and long texts, ties, repeated rows, clashing extra columns and empty tables, beside brute force."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefgraph.llm import bpe, decontam, licenses, quality, sharding, suffix_dedup, topk, toxicity, warc
from prefgraph.llm.queries import tokenizer_path

TEXTS = [None, "", "Ab, c\n", "Ab, c\n", "é日本 <|endoftext|> 's", "x " * 3000, "the quick brown fox jumps over the lazy dog again and again"]
SCHEMA = "doc_id long, text string, w string, hits int, row string, id long, c string, t1 long, size string"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "w", 1, "r", 7, "c", 1, "s") for i, t in enumerate(TEXTS)] + [(None, "no id", *[None] * 7), (2, "Ab, c\n", *[None] * 7)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_sharding(docs, none):
    rows = sharding.shard_documents(docs, 4).collect()
    counts = [sum(r.shard == k for r in rows) for k in range(4)]
    assert len(rows) == 9 and max(counts) - min(counts) <= 1 and all(sorted(r.slot for r in rows if r.shard == k) == list(range(counts[k])) for k in range(4))
    assert {r.size for r in rows if r.doc_id == 0} == {16} and {r.text_crc32 for r in rows if r.doc_id == 2} == {zlib.crc32(b"Ab, c\n")}
    assert sharding.shard_documents(none).collect() == []
    for n in (1, 2, 7, 1000):
        assert sorted(sharding.permute(np.arange(n), n).tolist()) == list(range(n))
        assert all(sharding.row_at(*sharding.place(r, n, 4), n, 4) == r for r in range(0, n, 13))


def test_bpe(docs, none):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    for r in bpe.encode_documents(docs, tokenizer_path(), with_ids=True).filter("doc_id is not null").collect():
        ids = t.encode(TEXTS[r.doc_id] or "", add_special_tokens=False).ids
        assert np.frombuffer(r.ids, "<u4").tolist() == ids and r.n_tokens == len(ids)
        assert r.decoded_sha256 == hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert bpe.encode_documents(none, tokenizer_path()).collect() == []


def test_decontamination(spark, docs, none):
    items = spark.createDataFrame([(1, "QUICK brown fox jumps over the lazy dog again and"), (2, "ab C"), (3, None), (4, ""), (22, "ab c")], "item_id long, text string")
    digest = lambda s: hashlib.sha256(s.encode()).hexdigest()
    for most in (200_000, 0):
        got = {(r.doc_id, r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) for r in decontam.report(docs, items, max_set=most).collect()}
        assert {(2, 2, 2, 2, digest("2,22"), True), (6, 12, 10, 1, digest("1"), True), (0, 0, 0, 0, digest(""), False), (None, 2, 0, 0, digest(""), False)} <= got
        assert decontam.report(none, items, max_set=most).collect() == []
    assert {r.doc_id for r in decontam.remove_documents(docs, items).collect()} == {0, 1, 4, 5, None} and decontam.remove_documents(docs, items).columns == docs.columns
    assert {r.text for r in decontam.remove_spans(docs, items).filter("doc_id = 6").collect()} == {"the again"}
    assert decontam.remove_documents(docs, items.limit(0)).count() == 9


def test_licenses(spark, docs, none):
    mit = licenses.KNOWN["MIT"]
    more = docs.unionByName(spark.createDataFrame([(50, "Copyright (c) 2020 Someone\n" + mit.upper().replace(",", " ;")), (51, mit.replace("sublicense", "sublicence")), (52, mit + " or not")], "doc_id long, text string"), allowMissingColumns=True)
    assert {r.doc_id: r.license_id for r in licenses.scan_documents(more).filter("doc_id >= 50").collect()} == {50: "MIT", 51: "MIT", 52: None}
    assert licenses.scan_documents(more).filter("doc_id < 50 or doc_id is null").filter("is_license").isEmpty() and licenses.scan_documents(none).isEmpty()
    assert licenses.remove_licenses(more).count() == 10


def test_warc(spark):
    body = "<p>" + "é" * 100
    rows = [(5, "http://a b", body), (3, None, body), (9, "u", body), (4, "u", None), (6, "u", "short"), (7, "u", "short"), (None, "u", "x" * 200), (8, "u", "\r\n\r\nWARC/1.1" * 20)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("d"))
    got = {r.page_id: (r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in warc.archive_pages(pages).collect()}
    for p, _, h in rows:
        raw = (h or "").encode()
        assert got[p] == (len(raw), hashlib.sha256(raw).hexdigest(), *(("revisit", 3) if p in (5, 9) else ("response", None)))
    assert warc.archive_pages(pages.limit(0)).collect() == []
    assert list(warc.coalesce_ranges([(0, 5), (5, 5), (100, 5)], gap=10, most=50)) == [(0, 10, [0, 1]), (100, 105, [2])]


def test_top_k(spark):
    r = random.Random(2)
    rows = [(i, [r.uniform(-1, 1) for _ in range(6)]) for i in range(120)] + [(200, None), (201, [1.0] * 5 + [float("nan")]), (202, [1.0, None]), (203, [1.0, 2.0]), (204, [0.5, 0.5]), (None, [1.0] * 6)]
    rows += [(300, rows[7][1]), (301, rows[7][1])]
    got = {}
    for x in topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("c", F.lit(1)), F.col("vec_id") % 50 == 0).collect():
        got.setdefault(x.query_id, []).append((x.rank, x.vec_id, x.score))
    fine = {i: [int(np.floor(256 * x)) for x in v] for i, v in rows if i is not None and v and all(x is not None and x == x for x in v)}
    for q in [i for i in fine if i % 50 == 0]:
        best = sorted((-sum(a * b for a, b in zip(fine[q], v, strict=True)), i) for i, v in fine.items() if i != q and len(v) == len(fine[q]))[:5]
        assert sorted(got[q]) == [(k, i, -s) for k, (s, i) in enumerate(best, 1)]
    assert topk.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.col("vec_id") % 50 == 0).collect() == []


def test_classifiers(spark, docs, none):
    r = random.Random(4)
    words = ["alpha", "beta", "gamma", "delta", "omega", "sigma", "kappa"]
    rows = [(i, " ".join(r.choices(words, k=40)) + (" vile rotten" if i % 3 == 0 else "") if i % 2 else "!!! ### $$$ " * 20 + (" vile rotten" if i % 3 == 0 else "")) for i in range(400)]
    big = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2, int(i % 3 == 0)) for i in range(400)] + [(None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    for module, col, cut in ((toxicity, "toxic", 0.5), (quality, "quality", 0.7)):
        got = module.score_documents(big, labels).join(labels, "doc_id").filter("held_out").select("predicted", "score", F.col(col).alias("y")).filter("y is not null").collect()
        assert sum(x.predicted == x.y for x in got) / len(got) > 0.95 and all(0 <= x.score <= 1 and x.predicted == (x.score >= cut) for x in got)
        odd = module.score_documents(docs, labels).collect()
        assert len(odd) == 9 and all(0 <= x.score <= 1 for x in odd)
        assert module.score_documents(none, labels).collect() == [] and module.score_documents(docs, labels.limit(0)).count() == 9


def test_repeats_edges(docs, none):
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans) for r in suffix_dedup.report(docs).collect()}
    assert got[0] == (0, 0, 0) and got[5] == (6000, 6000, 1) and got[6][1:] == (0, 0)
    assert suffix_dedup.report(none).collect() == []
    assert suffix_dedup.remove_repeats(docs).columns == docs.columns
