"""A corpus pipeline: toxic documents go, one document of each near-duplicate group stays, repeated passages are cut, documents with
benchmark passages go, and what is left is tokenised.

Null texts count as empty: they are not toxic, near nothing, without repeats or benchmark passages, and have no tokens. Rows of a null doc_id
stay; of rows repeated with one doc_id all stay or go together; extra columns go through all stages but the last. An empty table gives an
empty table at every stage. Ties among near duplicates go to the least doc_id.

Each stage takes (spark, docs, sf_dir). Its result has to be written before the next stage is called on what was written: a stage
deletes the scratch tables of the one before. ``run`` does so.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefgraph.llm import bpe, common, decontam, ngram_join, suffix_dedup, toxicity
from prefgraph.llm.queries import tokenizer_path

#: The least repeated span that the cut takes: passages of over 50 words have it where a word and its space take five bytes on average. At 200, a short
#: text that only repeats itself lost all of it. op3's own report keeps its 400 bytes.
PASSAGE_BYTES, PASSAGE_GRAM = 250, 48

_LEFT: list[str] = []


def _alone(stage: Callable[[SparkSession, DataFrame, str], DataFrame]) -> Callable[[SparkSession, DataFrame, str], DataFrame]:
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        while _LEFT:
            common.delete_path(spark, _LEFT.pop())
        before = set(common.live(spark))
        out = stage(spark, docs, sf_dir)
        _LEFT.extend(p for p in common.live(spark) if p not in before)
        return out

    run_stage.__name__, run_stage.__doc__ = stage.__name__, stage.__doc__
    return run_stage


@_alone
def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier scores below 0.5; it learns from the labelled ones of docs, as op2 does."""
    model = toxicity.train(docs, common.read_table(spark, sf_dir, "labels"))
    return toxicity.with_score(docs, model, "_toxicity").filter(F.col("_toxicity") < 0.5).drop("_toxicity")


@_alone
def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the least doc_id of each component of similar documents."""
    return ngram_join.one_of_each(docs)


@_alone
def cut_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without their spans of PASSAGE_BYTES or more that occur elsewhere. A document that is all repeats stays, with an empty text."""
    return suffix_dedup.remove_repeats(docs, PASSAGE_BYTES, PASSAGE_GRAM)


@_alone
def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any window of the benchmark."""
    return decontam.remove_documents(docs, common.read_table(spark, sf_dir, "benchmark"))


@_alone
def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of each document."""
    return bpe.encode_documents(docs, tokenizer_path())


STAGES = [
    ("toxicity", drop_toxic), ("ngram_jaccard_join", keep_one_of_each), ("suffix_dedup", cut_repeats), ("decontamination", drop_contaminated), ("bpe", tokenize),
]
ORACLE_SQL = None  # a trained classifier is no SQL; tests hold the stages against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over documents."""
    docs = common.read_table(spark, sf_dir, "documents")
    folder = common.scratch_path(spark, "pipeline", tracked=False)
    for k, (name, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}-{name}")
        docs = spark.read.parquet(f"{folder}/{k}-{name}")
    return docs
