"""Toxicity: a linear classifier on character n-grams whose features are scaled by naive Bayes log-count ratios.

A text is the set of its byte n-grams of three lengths (A-Z in lower case), hashed to ``DIMS`` features. Over the training sample, r is
the log of the ratio of each feature's smoothed shares in the two classes; logistic regression with an L2 penalty learns weights
on features scaled by r. Scoring is a sum of ``weight * r`` over a text's features: one lookup a distinct n-gram.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import row_blocks, text_buffers, tidy
from .learn import fold, labelled_sample, minimize, sigmoid

LENGTHS = (3, 4, 5)
BITS = 18
DIMS = 1 << BITS
TRAIN_ROWS = 4000  # the bound of the labelled sample, and
TRAIN_BYTES = 16 << 20  # of its texts
BLOCK = 1 << 19
CHUNK = 1 << 20  # features that a step of training takes at once
_LOW = np.arange(256, dtype=np.uint8)
_LOW[65:91] += 32


def grams(raw: np.ndarray) -> list[np.ndarray]:
    """For each length n the hashed features of all n-grams of raw, by place."""
    low = _LOW[raw].astype(np.uint64)
    out, packed = [], np.zeros(len(low), np.uint64)
    with np.errstate(over="ignore"):
        for n in range(1, max(LENGTHS) + 1):
            if len(low) < n:
                out += [np.empty(0, np.int32)] * (n in LENGTHS)
                continue
            packed = (packed[: len(low) - n + 1] << np.uint64(8)) | low[n - 1 :]
            if n in LENGTHS:
                out.append((((packed * np.uint64(0x9E3779B97F4A7C15)) ^ np.uint64(n)) * np.uint64(0xC2B2AE3D27D4EB4F) >> np.uint64(64 - BITS)).astype(np.int32))
    return out


class Features:
    """Distinct features of texts: each place is stamped into its feature's slot, and the last place stays."""

    def __init__(self) -> None:
        self.stamp = np.zeros(DIMS, np.int32)

    def of_block(self, raw: np.ndarray, bounds: np.ndarray) -> Iterator[np.ndarray]:
        by_length = grams(raw)
        for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            found = np.concatenate([g[lo : max(lo, hi - n + 1)] for n, g in zip(LENGTHS, by_length, strict=True)])
            places = np.arange(len(found), dtype=np.int32)
            self.stamp[found] = places
            yield found[self.stamp[found] == places]


def _blocks(column: pa.Array) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    raw, bounds = text_buffers(column)
    for i, j in row_blocks(bounds, BLOCK):
        yield raw[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i]


@dataclass
class Model:
    weights: np.ndarray  # float32 by feature, the ratio included
    bias: float

    def scores(self, column: pa.Array) -> np.ndarray:
        features, out = Features(), []
        for raw, bounds in _blocks(column):
            out += [float(self.weights[f].sum(dtype=np.float64)) for f in features.of_block(raw, bounds)]
        return sigmoid(np.array(out, np.float64) + self.bias)


def fit(sample: DataFrame, counts: dict[int, int], smoothing: float = 1.0, penalty: float = 2e-4) -> Model:
    """Learn from sample(text, y), whose texts become at most DIMS features each on the executors; counts give the classes' prior.

    With labels of one class only, or none, every text gets the prior's score.
    """

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = Features()
        for batch in batches:
            found = [f.astype("<i4").tobytes() for raw, bounds in _blocks(batch.column("text")) for f in made.of_block(raw, bounds)]
            yield pa.RecordBatch.from_arrays([batch.column("y"), pa.array(found, pa.binary())], ["y", "f"])

    rows = sample.mapInArrow(tidy(features), "y int, f binary").toArrow()
    y = np.array(rows.column("y").to_pylist(), np.float64)
    total, positive = sum(counts.values()), counts.get(1, 0)
    prior = np.log((positive + 0.5) / (total - positive + 0.5))
    if not len(y) or y.min() == y.max():
        return Model(np.zeros(DIMS, np.float32), float(prior))
    column = rows.column("f").combine_chunks()
    del rows
    bounds = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64) // 4
    every = np.frombuffer(column.buffers()[2], "<i4") if len(column) and bounds[-1] else np.empty(0, "<i4")

    def chunks() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(features, their rows) of some rows at a time, as views of what the executors sent."""
        for i, j in row_blocks(bounds, CHUNK):
            yield every[bounds[i] : bounds[j]], np.repeat(np.arange(i, j, dtype=np.int32), np.diff(bounds[i : j + 1]))

    up, down = np.full(DIMS, smoothing), np.full(DIMS, smoothing)
    for at, row in chunks():
        up += np.bincount(at, weights=y[row], minlength=DIMS)
        down += np.bincount(at, weights=1 - y[row], minlength=DIMS)
    ratio = np.log(up / up.sum()) - np.log(down / down.sum())
    share = {1: positive / total, 0: 1 - positive / total}
    weight = np.where(y == 1, share[1] / y.mean(), share[0] / (1 - y.mean())) / len(y)

    def loss(v: np.ndarray) -> tuple[float, np.ndarray]:
        z, scaled = np.full(len(y), v[DIMS]), v[:DIMS] * ratio
        for at, row in chunks():
            z += np.bincount(row, weights=scaled[at], minlength=len(y))
        error = weight * (sigmoid(z) - y)
        grad = np.zeros(DIMS)
        for at, row in chunks():
            grad += np.bincount(at, weights=error[row], minlength=DIMS)
        value = float((weight * (np.logaddexp(0, z) - y * z)).sum() + 0.5 * penalty * (v[:DIMS] @ v[:DIMS]))
        return value, np.r_[grad * ratio + penalty * v[:DIMS], error.sum()]

    v = minimize(loss, np.r_[np.zeros(DIMS), prior], steps=40)
    return Model((v[:DIMS] * ratio).astype(np.float32), float(v[DIMS]))


def train(docs: DataFrame, labels: DataFrame, folds: int = 5, held: int = 0, rows: int = TRAIN_ROWS) -> Model:
    """A model of labels.toxic from labels whose fold is not held; only texts and labels are inputs."""
    return fit(*labelled_sample(docs, labels, "toxic", lambda d: fold(d, folds) != held, rows, TRAIN_BYTES))


def with_score(docs: DataFrame, model: Model, column: str = "score") -> DataFrame:
    """docs with a score from 0 to 1 for each whole text; null and empty texts have no features."""
    names = [c for c in docs.columns if c != column]
    schema = docs.select(*[F.col(f"`{c}`") for c in names]).withColumn(column, F.lit(0.0).cast("double")).schema

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = [batch.column(c) for c in names]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(model.scores(batch.column("text")), pa.float64())], [*names, column])

    return docs.select(*[F.col(f"`{c}`") for c in names]).mapInArrow(tidy(score), schema)


def score_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs(doc_id, text).

    Null or repeated doc_ids stay rows (a null id is in no fold: held_out false); extra columns are ignored; no rows give none.
    """
    scored = with_score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text")), train(docs, labels))
    held = F.coalesce(fold(F.col("doc_id"), 5) == 0, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
