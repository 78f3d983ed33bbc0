"""op3's 400 bytes and the pipeline's shorter cut, on passages of over 50 words that two documents share."""

import hashlib
import random

import corpus_pipeline
from prefgraph.llm import suffix_dedup


def test_passages_of_over_fifty_words(spark):
    """Of passages of over 50 words op3 takes those of 400 bytes and more, whole, and keeps 399; the pipeline's cut takes them all."""
    r = random.Random(11)
    line = lambda n: " ".join("".join(r.choices("abcdefghijklm", k=4)) for _ in range(n))
    passages = {n: line(n // 5 + 1)[:n] for n in (260, 399, 400, 700)}
    assert all(len(p.split()) > 50 for p in passages.values())
    around = [(k, n, f"{line(40)} {'<('[k]}", f"{'>)'[k]} {line(30)}") for n in passages for k in (0, 1)]
    rows = [(n * 10 + k, head + passages[n] + tail) for k, n, head, tail in around]
    docs = spark.createDataFrame([*rows, (1, line(300))], "doc_id long, text string")
    sha = lambda text: hashlib.sha256(text.encode()).hexdigest()
    want = {n * 10 + k: (n, 1, sha(head + tail)) if n >= 400 else (0, 0, sha(head + passages[n] + tail)) for k, n, head, tail in around}
    got = {x.doc_id: (x.n_removed, x.n_spans, x.kept_sha256) for x in suffix_dedup.report(docs).collect()}
    assert got.pop(1)[:2] == (0, 0) and got == want
    cut = {x.doc_id: x.text for x in suffix_dedup.remove_repeats(docs, corpus_pipeline.PASSAGE_BYTES, corpus_pipeline.PASSAGE_GRAM).collect()}
    assert len(cut.pop(1).split()) == 300 and cut == {n * 10 + k: head + tail for k, n, head, tail in around}
