"""Quality: documents ranked by a Bradley-Terry model of preference pairs.

A pair is a document labelled 1 over one labelled 0; the chance that a wins over b is the logistic function of the difference of
their scores, which are linear in the features. The features are shares of character classes, of distinct byte windows and the like,
each cut at quantiles of the labelled documents (ranks exact to one in 10,000). All labelled documents take part: they are dealt out to blocks by a
hash, every pair of a block counts, and Newton's method adds up blocks. The raw score becomes one of 0 to 1 so that the quantile of the labelled
documents at the share of label 0 lies at the decision threshold. ``fit`` does the like for rows in memory, by drawn pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, row_blocks, text_buffers
from .learn import fold, minimize, sigmoid

PAIRS = 40_000
BLOCK_ROWS = 1024  # of the rarer label in a block
WIDTH = 18
CUTS = 9
THRESHOLD = 0.7
BLOCK = 1 << 20
_WINDOW_BITS = 16


def _class(*ranges: tuple[int, int]) -> np.ndarray:
    out = np.zeros(256, np.int8)
    for a, b in ranges:
        out[a : b + 1] = 1
    return out


_CLASSES = [
    _class((65, 90)), _class((97, 122)), _class((48, 57)), _class((32, 32)), _class((10, 10)), _class((46, 46)), _class((44, 44)), _class((33, 33), (63, 63)),
    _class((124, 124)), _class((35, 38), (42, 43), (60, 64), (91, 96), (123, 123), (125, 126)), _class((0, 8), (11, 31), (127, 127)), _class((128, 255)),
    _class((39, 41), (45, 45), (47, 47), (58, 59), (34, 34)),
]


def features(raw: np.ndarray, bounds: np.ndarray, stamp: np.ndarray) -> np.ndarray:
    """A row of numbers for each text of a block."""
    size = np.diff(bounds).astype(np.float64)
    least = np.maximum(size, 1)
    columns = [np.log1p(size)]
    for c in _CLASSES:
        sums = np.r_[0, np.cumsum(c[raw], dtype=np.int64)]
        columns.append((sums[bounds[1:]] - sums[bounds[:-1]]) / least)
    blank = (raw == 32) | ((raw >= 9) & (raw <= 13))
    begins = ~blank
    begins[1:] &= blank[:-1]
    begins[bounds[:-1][size > 0]] = ~blank[bounds[:-1][size > 0]]
    words = np.r_[0, np.cumsum(begins, dtype=np.int64)]
    words = (words[bounds[1:]] - words[bounds[:-1]]).astype(np.float64)
    columns += [np.log1p(words), least / np.maximum(words, 1)]
    same = np.r_[False, raw[1:] == raw[:-1]] if len(raw) else np.zeros(0, bool)
    runs = np.r_[0, np.cumsum(same, dtype=np.int64)]
    columns.append((runs[bounds[1:]] - runs[bounds[:-1]]) / least)
    distinct = np.ones(len(size))
    if len(raw) >= 8:
        wide = np.lib.stride_tricks.sliding_window_view(raw, 8)[:, ::1].copy().view(np.uint64).ravel()
        with np.errstate(over="ignore"):
            slot = ((wide * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - _WINDOW_BITS)).astype(np.int32)
        for i, (lo, hi) in enumerate(zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)):
            if hi - lo >= 8:
                found = slot[lo : hi - 7]
                places = np.arange(len(found), dtype=np.int32)
                stamp[found] = places
                distinct[i] = np.count_nonzero(stamp[found] == places) / min(len(found), 1 << _WINDOW_BITS)
    columns.append(distinct)
    return np.stack(columns, axis=1)


def text_features(column: pa.Array) -> np.ndarray:
    stamp, out = np.zeros(1 << _WINDOW_BITS, np.int32), []
    raw, bounds = text_buffers(column)
    for i, j in row_blocks(bounds, BLOCK):
        out.append(features(raw[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i], stamp))
    return np.concatenate(out) if out else np.empty((0, len(_CLASSES) + 5))


@dataclass
class Ranker:
    cuts: np.ndarray  # features x cuts
    weights: np.ndarray  # features x (cuts + 1)
    middle: float  # the raw score that is at the threshold

    def raw(self, x: np.ndarray) -> np.ndarray:
        return sum((self.weights[k][np.searchsorted(self.cuts[k], x[:, k], side="right")] for k in range(len(self.cuts))), np.zeros(len(x)))

    def score(self, x: np.ndarray) -> np.ndarray:
        return sigmoid(self.raw(x) - self.middle + np.log(THRESHOLD / (1 - THRESHOLD)))


def fit(x: np.ndarray, y: np.ndarray, counts: dict[int, int], pairs: int = PAIRS, penalty: float = 1e-3, seed: int = 11) -> Ranker:
    """Learn from rows x with labels y. With one class only, or no rows, every text gets the score of that class's share."""
    total = max(1, sum(counts.values()))
    share = counts.get(0, 0) / total
    width = x.shape[1]
    if not len(y) or y.min() == y.max():
        target = np.clip(1 - share, 0.01, 0.99) if sum(counts.values()) else 0.5
        return Ranker(np.zeros((width, CUTS)), np.zeros((width, CUTS + 1)), float(np.log(THRESHOLD / (1 - THRESHOLD)) - np.log(target / (1 - target))))
    bad, good = np.flatnonzero(y == 0), np.flatnonzero(y == 1)
    even = np.r_[np.quantile(x[bad], np.linspace(0.1, 0.9, 4), axis=0), np.quantile(x[good], np.linspace(0.02, 0.98, CUTS - 4), axis=0)]
    cuts = np.sort(even, axis=0).T.copy()
    bins = np.stack([np.searchsorted(cuts[k], x[:, k], side="right") + k * (CUTS + 1) for k in range(width)], axis=1)
    rng = np.random.default_rng(seed)
    winner, loser = bins[good[rng.integers(len(good), size=pairs)]], bins[bad[rng.integers(len(bad), size=pairs)]]
    size = width * (CUTS + 1)

    def loss(v: np.ndarray) -> tuple[float, np.ndarray]:
        margin = v[winner].sum(axis=1) - v[loser].sum(axis=1)
        pull = sigmoid(-margin) / pairs
        each = np.repeat(pull, width)
        grad = np.bincount(loser.ravel(), weights=each, minlength=size) - np.bincount(winner.ravel(), weights=each, minlength=size)
        return float(np.logaddexp(0, -margin).mean() + 0.5 * penalty * (v @ v)), grad + penalty * v

    ranker = Ranker(cuts, minimize(loss, np.zeros(size), steps=80).reshape(width, CUTS + 1), 0.0)
    s = ranker.raw(x)
    weight = np.where(y == 1, (1 - share) / len(good), share / len(bad))  # the sample's classes at their true shares
    by = np.argsort(s, kind="stable")
    at = min(int(np.searchsorted(np.cumsum(weight[by]), share)), len(s) - 2)
    ranker.middle = float((s[by][at] + s[by][at + 1]) / 2)
    return ranker


def featured(docs: DataFrame) -> DataFrame:
    """(doc_id, x) of every row of docs(doc_id, text), stored; x: its features as 32-bit numbers."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = text_features(batch.column("text")).astype(np.float32)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "x"])

    return materialize(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text")).mapInArrow(made, "doc_id long, x binary"), "features")


def _rows(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.float32).reshape(-1, WIDTH).astype(np.float64)


def _quantiles(labelled: DataFrame) -> np.ndarray:
    """Features x CUTS: quantiles of all labelled rows, of both labels."""
    names = [f"f{k}" for k in range(WIDTH)]

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("y"), *[pa.array(c, pa.float64()) for c in _rows(batch.column("x")).T.copy()]], ["y", *names])

    wide = labelled.select("y", "x").mapInArrow(spread, "y int, " + ", ".join(f"{n} double" for n in names))
    out = []
    for y, at in ((0, np.linspace(0.1, 0.9, 4)), (1, np.linspace(0.02, 0.98, CUTS - 4))):
        row = wide.filter(F.col("y") == y).agg(*[F.percentile_approx(n, [float(q) for q in at], 10_000).alias(n) for n in names]).first()
        out.append(np.array([row[n] for n in names]))
    return np.sort(np.concatenate(out, axis=1), axis=1)


def _bins(cuts: np.ndarray, x: np.ndarray) -> np.ndarray:
    return np.stack([np.searchsorted(cuts[k], x[:, k], side="right") + k * (CUTS + 1) for k in range(WIDTH)], axis=1).astype(np.uint8)


def _sums(good: np.ndarray, bad: np.ndarray, v: np.ndarray) -> tuple[float, int, np.ndarray, np.ndarray]:
    """(loss, pairs, gradient, Hessian) summed over all pairs of a good and a bad row of bins."""
    size, loss = len(v), 0.0
    grad, hess = np.zeros(size), np.zeros((size, size))

    def one_hot(rows: np.ndarray) -> np.ndarray:
        out = np.zeros((len(rows), size))
        np.put_along_axis(out, rows.astype(np.int64), 1.0, axis=1)
        return out

    for i in range(0, len(good), BLOCK_ROWS):
        g = one_hot(good[i : i + BLOCK_ROWS])
        for j in range(0, len(bad), BLOCK_ROWS):
            b = one_hot(bad[j : j + BLOCK_ROWS])
            margin = (g @ v)[:, None] - (b @ v)[None, :]
            pull = sigmoid(-margin)
            bend = pull * (1 - pull)
            loss += float(np.logaddexp(0, -margin).sum())
            grad += b.T @ pull.sum(axis=0) - g.T @ pull.sum(axis=1)
            cross = g.T @ (bend @ b)
            hess += (g.T * bend.sum(axis=1)) @ g + (b.T * bend.sum(axis=0)) @ b - cross - cross.T
    return loss, len(good) * len(bad), grad, hess


def _newton(blocks: DataFrame, penalty: float = 1e-3, steps: int = 20) -> np.ndarray:
    """The weights that minimise the mean loss of all pairs of the blocks(good, bad): one job a step."""
    size = WIDTH * (CUTS + 1)

    def at(v: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            loss, pairs, grad, hess = 0.0, 0, np.zeros(size), np.zeros((size, size))
            for batch in batches:
                for g, b in zip(batch.column("good").to_pylist(), batch.column("bad").to_pylist(), strict=True):
                    one = _sums(*[np.frombuffer(x, np.uint8).reshape(-1, WIDTH) for x in (g, b)], v)
                    loss, pairs, grad, hess = loss + one[0], pairs + one[1], grad + one[2], hess + one[3]
            if pairs:
                yield pa.RecordBatch.from_arrays([pa.array([loss]), pa.array([pairs], pa.int64()), pa.array([np.r_[grad, hess.ravel()].tobytes()], pa.binary())], ["loss", "pairs", "x"])

        loss, pairs, both = 0.0, 0, np.zeros(size + size * size)
        for r in blocks.mapInArrow(run, "loss double, pairs long, x binary").collect():
            loss, pairs, both = loss + r.loss, pairs + r.pairs, both + np.frombuffer(r.x)
        both /= pairs
        return loss / pairs + 0.5 * penalty * float(v @ v), both[:size] + penalty * v, both[size:].reshape(size, size) + penalty * np.eye(size)

    v = np.zeros(size)
    value, grad, hess = at(v)
    for _ in range(steps):
        if np.abs(grad).max() < 1e-6:
            break
        d, part = np.linalg.solve(hess, grad), 1.0
        while part > 1e-4:
            new = at(v - part * d)
            if new[0] <= value - 1e-4 * part * float(grad @ d):
                break
            part /= 2
        else:
            break
        v, (value, grad, hess) = v - part * d, new
    return v


def _nth(scores: DataFrame, low: float, high: float, rank: int) -> float:
    """The score of a rank from 1 among all rows of scores(s), by three counts of ever finer bins."""
    for _ in range(3):
        cell = (high - low) / 4096
        place = F.least(F.greatest(F.floor((F.col("s") - low) / cell), F.lit(-1)), F.lit(4096)).cast("int")
        before = 0
        for p, n in sorted(tuple(r) for r in scores.groupBy(place.alias("p")).count().collect()):
            if before + n >= rank:
                break
            before += n
        if not 0 <= p < 4096:  # rounding at an end
            return low if p < 0 else high
        low, high = low + p * cell, low + (p + 1) * cell
        if high - low < 1e-12 * max(1.0, abs(low)):
            break
    return (low + high) / 2


def train(feats: DataFrame, labels: DataFrame, folds: int = 4, held: int = 2) -> Ranker:
    """A ranker of labels.quality from all labels whose fold is not held; feats: featured(docs)."""
    ids = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("y")).filter(F.col("doc_id").isNotNull() & F.col("y").isin(0, 1) & (fold(F.col("doc_id"), folds) != held))
    labelled = materialize(feats.join(ids.groupBy("doc_id").agg(F.max("y").alias("y")), "doc_id"), "labelled")
    counts = {r.y: r["n"] for r in labelled.groupBy("y").agg(F.count(F.lit(1)).alias("n")).collect()}
    n = sum(counts.values())
    if len(counts) < 2:
        discard(labelled)
        return fit(np.empty((0, WIDTH)), np.empty(0, np.int64), counts)
    cuts = _quantiles(labelled)

    def block(rows: pa.Table) -> pa.Table:
        bins, y = _bins(cuts, _rows(rows.column("x"))), rows.column("y").to_numpy()
        return pa.table({"good": pa.array([bins[y == 1].tobytes()], pa.binary()), "bad": pa.array([bins[y == 0].tobytes()], pa.binary())})

    of = F.pmod(F.xxhash64("doc_id"), F.lit(max(1, min(counts.values()) // BLOCK_ROWS)))
    blocks = materialize(labelled.select("y", "x", of.alias("block")).groupBy("block").applyInArrow(block, "good binary, bad binary"), "blocks")
    weights = _newton(blocks).reshape(WIDTH, CUTS + 1)
    ranker = Ranker(cuts, weights, 0.0)

    def raw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(ranker.raw(_rows(batch.column("x"))), pa.float64())], ["s"])

    scores = materialize(labelled.select("x").mapInArrow(raw, "s double"), "scores")
    low, high = float(weights.min(axis=1).sum()) - 1e-6, float(weights.max(axis=1).sum()) + 1e-6
    ends = [_nth(scores, low, high, min(max(1, k), n)) for k in (counts[0], counts[0] + 1)]
    for stored in (labelled, blocks, scores):
        discard(stored)
    return Ranker(cuts, weights, sum(ends) / 2)


def score_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs(doc_id, text).

    Null and empty texts are texts of no bytes. Null or repeated doc_ids stay rows (a null id is in no fold: held_out false); extra
    columns are ignored; no rows give none.
    """
    feats = featured(docs)
    ranker = train(feats, labels)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(ranker.score(_rows(batch.column("x"))), pa.float64())], ["doc_id", "score"])

    scored = feats.mapInArrow(score, "doc_id long, score double")
    held = F.coalesce(fold(F.col("doc_id"), 4) == 2, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
