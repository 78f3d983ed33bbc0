"""Each stage on a small corpus: its decisions take effect and clean documents stay."""

import random

import corpus_pipeline as pipeline

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages_by_hand(spark, tmp_path):
    word = lambda i: "".join(chr(97 + (i * k) % 26) for k in (7, 11, 3, 17))
    text = lambda a, n: " ".join(word(a * 1000 + i * i + i * a) for i in range(n))
    shared = text(77, 120)
    rows = [(1, text(1, 60)), (2, text(1, 60).upper()), (3, text(3, 90) + " " + shared), (4, text(4, 95) + " " + shared), (5, text(5, 50)), (6, None), (7, "")]
    plain = lambda i: " ".join(random.Random(i).choices([word(7 * k) for k in range(40)], k=30))
    rows += [(i, plain(i) + " nastyword wretched") for i in range(10, 60)] + [(i, plain(i)) for i in range(60, 130)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    folder = str(tmp_path)
    spark.createDataFrame([(i, 1, int(i < 60)) for i in range(10, 130)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    spark.createDataFrame([(1, text(5, 50)[30:200])], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    kept = {}
    for k, (name, stage) in enumerate(pipeline.STAGES):
        stage(spark, docs, folder).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        kept[name] = {r.doc_id for r in docs.select("doc_id").collect()}
        if k < 4:
            assert docs.columns == COLUMNS
        if name == "suffix_dedup":
            texts = {r.doc_id: r.text for r in docs.collect()}
            assert shared[20:-20] not in texts[3] and shared[20:-20] not in texts[4] and texts[1] == rows[0][1] and texts[6] is None
    assert kept["toxicity"] == {i for i, _ in rows if not 10 <= i < 60}
    assert kept["ngram_jaccard_join"] == kept["toxicity"] - {2}
    assert kept["suffix_dedup"] == kept["ngram_jaccard_join"]
    assert kept["decontamination"] == kept["suffix_dedup"] - {5}
    assert kept["bpe"] == kept["decontamination"]
