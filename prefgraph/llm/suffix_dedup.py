"""Exact removal of repeated substrings by external, induced suffix sorting.

Every window of ``length`` bytes holds exactly one anchor: the leftmost of its k-grams of the least hash. So equal windows meet in the
group of their anchor's k-gram, at the same distance from it, and only suffixes of the anchors' surroundings have to be sorted:

1. An anchor's surroundings are all bytes of windows around it. A group with one occurrence has no repeat. Surroundings that occur
   twice as a whole repeat with all their windows. All others of a group of two or more are sorted.
2. Suffixes that begin at the anchors are sorted by Spark's external sort, partitioned by group, and get the lengths of the prefixes that
   they share with their predecessors.
3. The order of the suffixes one byte further left is induced from it: the tuples (class, preceding byte, rank) go to the queue of their
   byte in the order of ranks. The prefix length two suffixes share comes from the range minimum over the first order plus the bytes
   already induced. A window whose neighbour in the order shares ``length`` bytes repeats; a suffix alone in its class leaves.

Groups of more than ``HOT`` surroundings are divided by the bytes common to all windows of a range of distances. Surroundings of a chunk beyond
``CHUNK_BYTES`` lie in a file of the worker that is mapped, not in its memory.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import group_batches, materialize, mix, prefix_sums, release, row_blocks, span_hash, text_buffers, text_key, tidy

LENGTH = 400
GRAM = 64
BLOCK = 1 << 19
CHUNK_ROWS = 8_000
CHUNK_BYTES = 64 << 20
HOT, HOT_RANGES = 20_000, 8
_PLACE_BITS = 20
_STEP = (1 << _PLACE_BITS) - (1 << 13)
_U = np.uint64


def _window_min(v: np.ndarray, width: int) -> np.ndarray:
    """The minimum of each window of width values."""
    n = len(v)
    padded = np.full(-(-n // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[:n] = v
    cells = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(cells, axis=1).ravel()
    behind = np.minimum.accumulate(cells[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def anchors(raw: np.ndarray, bounds: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> dict[str, np.ndarray]:
    """text (its number), pos (in the text), left, right (bytes of the surroundings on both sides), fp and ctx hashes of all anchors."""
    width = length - gram + 1
    empty = {c: np.empty(0, np.int64) for c in ("text", "pos", "left", "right", "fp", "ctx")}
    if len(raw) < length:
        return empty
    sums = prefix_sums(raw)
    starts = np.arange(len(raw) - gram + 1)
    h = span_hash(sums, starts, starts + gram)
    ends = np.repeat(bounds[1:], np.diff(bounds))
    inside = np.arange(len(raw) - length + 1) + length <= ends[: len(raw) - length + 1]
    low = _U((1 << _PLACE_BITS) - 1)
    found = []
    for s in range(0, len(inside), _STEP):
        part = h[s : s + _STEP + width - 1]
        least = _window_min((part & ~low) | np.arange(len(part), dtype=_U), width)
        ok = inside[s : s + len(least)]
        found.append(np.unique(least[: len(ok)][ok] & low).astype(np.int64) + s)
    p = np.unique(np.concatenate(found))
    if not len(p):
        return empty
    text = np.searchsorted(bounds, p, side="right") - 1
    lo, hi = np.maximum(p - (width - 1), bounds[text]), np.minimum(p + length, bounds[text + 1])
    fp = h[p]
    ctx = mix(span_hash(sums, lo, hi) ^ mix(span_hash(sums, lo, p) + _U(0x51ED270B)))
    return {"text": text, "pos": p - bounds[text], "left": p - lo, "right": hi - p, "fp": fp.view(np.int64), "ctx": ctx.view(np.int64)}


_OCCURRENCE = "fp long, ctx long, n long, t1 long, t2 long, pos int, left int, right int"


def _occurrences(docs: DataFrame, length: int, gram: int, counted: bool) -> DataFrame:
    """Anchors of each distinct text of a block; counted: one row for each distinct surroundings of a block with their count."""

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, bounds = text_buffers(batch.column("text"))
            t1, t2 = (batch.column(c).to_numpy() for c in ("t1", "t2"))
            for i, j in row_blocks(bounds, BLOCK):
                a = anchors(raw[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i], length, gram)
                both = np.stack([t1[i:j], t2[i:j]], axis=1)
                _, first, copies = np.unique(both, axis=0, return_index=True, return_counts=True)
                weight = np.zeros(j - i, np.int64)
                weight[first] = copies
                keep = np.flatnonzero(weight[a["text"]])
                n = weight[a["text"]]
                if counted and len(keep):
                    by = keep[np.lexsort((a["ctx"][keep], a["fp"][keep]))]
                    new = np.r_[True, (a["fp"][by][1:] != a["fp"][by][:-1]) | (a["ctx"][by][1:] != a["ctx"][by][:-1])]
                    at = np.flatnonzero(new)
                    n[by[at]] = np.add.reduceat(n[by], at)
                    keep = by[at]
                text = a["text"][keep] + i
                columns = [a["fp"][keep], a["ctx"][keep], n[keep], t1[text], t2[text], *(a[c][keep].astype(np.int32) for c in ("pos", "left", "right"))]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["fp", "ctx", "n", "t1", "t2", "pos", "left", "right"])

    long_enough = docs.select(*text_key(F.col("text")), F.col("text").alias("text")).filter(F.octet_length("text") >= length)
    return long_enough.mapInArrow(tidy(find), _OCCURRENCE)


def _repeated_groups(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """The distinct surroundings of groups with two occurrences or more: stored, with twice (it occurs twice as a whole) and distinct (how many the group has).

    Counted by (fp, ctx) first, so that a group of a third of all rows is spread; its totals come from partial sums, and the join back
    is of two stored tables, which adaptive execution splits.
    """
    spark = docs.sparkSession
    firsts = [F.first(c).alias(c) for c in ("t1", "t2", "pos", "left", "right")]
    each = materialize(_occurrences(docs, length, gram, counted=True).groupBy("fp", "ctx").agg(F.sum("n").alias("n"), *firsts), "suffix-each")
    release(spark)
    totals = each.groupBy("fp").agg(F.sum("n").alias("total"), F.count(F.lit(1)).alias("distinct")).filter("total >= 2")
    totals = materialize(totals.select(F.col("fp").alias("_fp"), "distinct"), "suffix-totals")
    release(spark)
    kept = each.join(totals, each.fp == totals._fp).select("fp", "ctx", (F.col("n") >= 2).alias("twice"), "distinct", "t1", "t2", "pos", "left", "right")
    return materialize(kept, "suffix-groups")


def _cut_surroundings(length: int, gram: int, hot: int):
    """Texts with the anchors asked for become rows to sort: key (group), back and fwd (bytes left and right of the anchor), from and below (distances)."""
    width = length - gram + 1

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            size = 0
            for text, asked in zip(batch.column("text").to_pylist(), batch.column("asked").to_pylist(), strict=True):
                raw = text.encode()
                for a in asked:
                    p = a["pos"]
                    back, fwd = raw[p - a["left"] : p], raw[p : p + a["right"]]
                    if a["distinct"] <= hot:
                        out.append((a["fp"], a["fp"], a["ctx"], 0, width, back, fwd))
                        size += len(back) + len(fwd)
                    else:
                        edges = np.linspace(0, width, HOT_RANGES + 1).astype(int).tolist()
                        for lo, below in zip(edges[:-1], edges[1:], strict=True):
                            core = raw[max(0, p - lo) : p + length - below + 1]
                            if a["left"] >= lo and a["right"] >= length - below + 1:
                                key = int.from_bytes(hashlib.blake2b(core + bytes([lo % 256]), digest_size=8).digest(), "little", signed=True)
                                out.append((key, a["fp"], a["ctx"], lo, below, back, fwd))
                                size += len(back) + len(fwd)
                    if size > 8 << 20:
                        yield _surroundings(out)
                        out, size = [], 0
            yield _surroundings(out)

    return cut


_TYPES = (("key", pa.int64()), ("fp", pa.int64()), ("ctx", pa.int64()), ("from", pa.int32()), ("below", pa.int32()), ("back", pa.binary()), ("fwd", pa.binary()))


def _surroundings(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [()] * len(_TYPES)
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(columns, _TYPES, strict=True)], [n for n, _ in _TYPES])


def _matrix(column: pa.ChunkedArray, width: int, reverse: bool, file) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a binary column as rows of width (from the end, if reverse), and their lengths; mapped from file if that is given."""
    array = column.combine_chunks()
    array = array if isinstance(array, pa.Array) else pa.concat_arrays(array.chunks)
    _, offsets, data = array.buffers()
    bounds = np.frombuffer(offsets, np.int32)[array.offset : array.offset + len(array) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(1, np.uint8)
    lengths = np.diff(bounds)
    out = np.memmap(file, np.uint8, "w+", shape=(len(lengths), width)) if file else np.zeros((len(lengths), width), np.uint8)
    column_at = np.arange(width)
    for i in range(0, len(lengths), 4096):
        part = slice(i, i + 4096)
        at = bounds[1:][part, None] - 1 - column_at if reverse else bounds[:-1][part, None] + column_at
        out[part] = np.where(column_at < lengths[part, None], raw[np.clip(at, 0, len(raw) - 1)], 0)
    return out, lengths


class RangeMinimum:
    def __init__(self, values: np.ndarray) -> None:
        self.levels = [values]
        while (step := 1 << (len(self.levels) - 1)) * 2 <= len(values):
            last = self.levels[-1]
            self.levels.append(np.minimum(last[:-step], last[step:]))
        self.log = np.zeros(len(values) + 2, np.int64)
        for i in range(1, len(self.levels) + 1):
            self.log[1 << i :] = i
        size = len(values)
        self.table = np.stack([np.pad(x, (0, size - len(x))) for x in self.levels])

    def of(self, first: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Minima of values[first..last], both included."""
        k = self.log[last - first + 1]
        return np.minimum(self.table[k, first], self.table[k, last - (1 << k) + 1])


def induce(group: np.ndarray, shared: np.ndarray, back: np.ndarray, left: np.ndarray, begin: np.ndarray, below: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """The least and largest distance at which each suffix, sorted within groups, begins a repeated window; (length, -1) if none.

    shared: bytes shared with the predecessor, 0 at a group's first. back: bytes left of the anchor, nearest first; left: how many.
    """
    n = len(group)
    least, most = np.full(n, length, np.int64), np.full(n, -1, np.int64)
    minimum = RangeMinimum(shared.astype(np.int16))
    rank, cls = np.arange(n), group.copy()
    for d in range(back.shape[1] + 1):
        same = cls[1:] == cls[:-1]
        pairs = np.flatnonzero(same)
        if not len(pairs):
            break
        a, b = rank[pairs], rank[pairs + 1]
        hit = minimum.of(a + 1, b) >= length - d
        for side in (a[hit], b[hit]):
            side = side[(begin[side] <= d) & (d < below[side])]
            least[side] = np.minimum(least[side], d)
            most[side] = d
        keep = (np.r_[same, False] | np.r_[False, same]) & (left[rank] > d)
        rank, cls = rank[keep], cls[keep]
        if d == back.shape[1] or not len(rank):
            break
        queue = cls * 256 + back[rank, d]  # the queue of each tuple: its class, then its preceding byte
        if (queue[1:] < queue[:-1]).any():
            order = np.argsort(queue, kind="stable")
            rank, queue = rank[order], queue[order]
        cls = np.cumsum(np.r_[False, queue[1:] != queue[:-1]])
    return least, most


def _sort_chunks(length: int, gram: int):
    width = length - gram + 1

    def sort(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in group_batches(batches, "key", CHUNK_ROWS):
            key, fp, ctx, begin, below = (table.column(c).to_numpy() for c in ("key", "fp", "ctx", "from", "below"))
            mapped = len(key) * (length + width) > CHUNK_BYTES
            with tempfile.NamedTemporaryFile() as one, tempfile.NamedTemporaryFile() as two:
                fwd, right = _matrix(table.column("fwd"), length, False, one if mapped else None)
                back, left = _matrix(table.column("back"), width - 1, True, two if mapped else None)
                shared = np.zeros(len(key), np.int64)
                for i in range(1, len(key), 4096):
                    part = slice(i, min(i + 4096, len(key)))
                    before = slice(part.start - 1, part.stop - 1)
                    differs = fwd[part] != fwd[before]
                    first = np.where(differs.any(axis=1), differs.argmax(axis=1), length)
                    shared[part] = np.minimum(first, np.minimum(right[part], right[before]))
                shared[np.r_[True, key[1:] != key[:-1]]] = 0
                # rows of one (fp, ctx) in a group are one place in one text, read twice: the later ones leave
                again = np.r_[False, (key[1:] == key[:-1]) & (ctx[1:] == ctx[:-1]) & (fp[1:] == fp[:-1])]
                group = np.cumsum(np.r_[False, key[1:] != key[:-1]])
                if again.any():
                    stay = np.flatnonzero(~again)
                    lows = np.minimum.reduceat(shared, stay) if len(stay) else shared
                    shared = lows
                    group, back, left, begin, below, fp, ctx = group[stay], back[stay], left[stay], begin[stay], below[stay], fp[stay], ctx[stay]
                least, most = induce(group, shared, back, left, begin, below, length)
            hit = most >= 0
            yield pa.RecordBatch.from_arrays([pa.array(fp[hit]), pa.array(ctx[hit]), pa.array(least[hit].astype(np.int32)), pa.array(most[hit].astype(np.int32))], ["fp", "ctx", "least", "most"])

    return sort


def repeated_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT) -> DataFrame:
    """t1, t2, spans for each distinct text with repeats: spans, an array of (lo, hi), whose union is the bytes of repeated windows.

    A stored table; t1 and t2 are the text's keys (common.text_key).
    """
    spark = docs.sparkSession
    groups = _repeated_groups(docs, length, gram)
    release(spark)
    asked = groups.filter("distinct > 1").groupBy("t1", "t2").agg(F.collect_list(F.struct("fp", "ctx", "distinct", "pos", "left", "right")).alias("asked"))
    texts = docs.select(*text_key(F.col("text")), F.col("text").alias("text")).filter(F.octet_length("text") >= length).dropDuplicates(["t1", "t2"])
    cut = texts.join(asked, ["t1", "t2"]).select("text", "asked").mapInArrow(tidy(_cut_surroundings(length, gram, hot)), "key long, fp long, ctx long, `from` int, below int, back binary, fwd binary")
    ordered = cut.repartition("key").sortWithinPartitions("key", "fwd", "fp", "ctx")
    ranges = materialize(ordered.mapInArrow(tidy(_sort_chunks(length, gram)), "fp long, ctx long, least int, most int"), "suffix-ranges")
    release(spark)
    ranges = ranges.groupBy("fp", "ctx").agg(F.min("least").alias("least"), F.max("most").alias("most"))
    whole = groups.filter(F.col("twice") & (F.col("left") + F.col("right") >= length)).select("fp", "ctx", (length - F.least("right", F.lit(length))).alias("least"), F.col("left").alias("most"))
    marks = materialize(whole.unionByName(ranges.join(whole.select("fp", "ctx"), ["fp", "ctx"], "left_anti")), "suffix-marks")
    found = _occurrences(docs, length, gram, counted=False).join(marks, ["fp", "ctx"])
    spans = found.select("t1", "t2", (F.col("pos") - F.col("most")).alias("lo"), (F.col("pos") - F.col("least") + length).alias("hi")).distinct()
    stored = materialize(spans.groupBy("t1", "t2").agg(F.sort_array(F.collect_list(F.struct("lo", "hi"))).alias("spans")), "suffix-spans")
    release(spark)
    return stored


def merged(spans: list[dict]) -> list[tuple[int, int]]:
    """Maximal runs of sorted spans; spans that touch are one run."""
    out: list[tuple[int, int]] = []
    for s in spans:
        if out and s["lo"] <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], s["hi"]))
        else:
            out.append((s["lo"], s["hi"]))
    return out


def _kept(raw: bytes, runs: list[tuple[int, int]]) -> bytes:
    ends = [0, *(hi for _, hi in runs)]
    starts = [*(lo for lo, _ in runs), len(raw)]
    return b"".join(raw[i:j] for i, j in zip(ends, starts, strict=True))


def _to_characters(raw: bytes, runs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Runs shrunk to whole UTF-8 characters."""
    out = []
    for lo, hi in runs:
        while lo < hi and raw[lo] & 0xC0 == 0x80:
            lo += 1
        while hi > lo and hi < len(raw) and raw[hi] & 0xC0 == 0x80:
            hi -= 1
        out.append((lo, hi))
    return out


def report(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of docs(doc_id, text).

    A null text is empty; texts below length bytes lose nothing. Rows that repeat a whole text of length bytes or more lose all of
    it. Null and repeated doc_ids stay rows; extra columns are ignored; an empty table gives no rows.
    """
    spans = repeated_spans(docs, length, gram, hot)
    texts = docs.select(*text_key(F.col("text")), F.col("text").alias("text")).filter(F.octet_length("text") >= length).dropDuplicates(["t1", "t2"])

    def remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            removed, count, digest = [], [], []
            for text, found in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist(), strict=True):
                runs = merged(found)
                removed.append(sum(hi - lo for lo, hi in runs))
                count.append(len(runs))
                digest.append(hashlib.sha256(_kept(text.encode(), runs)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("t1"), batch.column("t2"), pa.array(removed, pa.int64()), pa.array(count, pa.int64()), pa.array(digest, pa.string())], ["t1", "t2", "n_removed", "n_spans", "kept"])

    cut = materialize(texts.join(spans, ["t1", "t2"]).select("t1", "t2", "text", "spans").mapInArrow(tidy(remove), "t1 long, t2 long, n_removed long, n_spans long, kept string"), "suffix-cut")
    release(docs.sparkSession)
    text = F.coalesce(F.col("text"), F.lit(""))
    every = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *text_key(F.col("text")), F.octet_length(text).cast("long").alias("n_bytes"), F.sha2(text.cast("binary"), 256).alias("whole"))
    return every.join(cut, ["t1", "t2"], "left").select(
        "doc_id", "n_bytes", F.coalesce("n_removed", F.lit(0).cast("long")).alias("n_removed"), F.coalesce("n_spans", F.lit(0).cast("long")).alias("n_spans"), F.coalesce("kept", "whole").alias("kept_sha256")
    )


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """docs with repeated spans cut from text, to whole characters, and n_chars (where there is one) counted anew; no row goes."""
    spans = repeated_spans(docs, length, gram).withColumnsRenamed({"t1": "_s1", "t2": "_s2", "spans": "_spans"})
    names = docs.columns
    keyed = docs.select(*[F.col(f"`{c}`") for c in names], *(k.alias(f"_k{i}") for i, k in enumerate(text_key(F.col("text")))))
    met = keyed.join(spans, (F.col("_k0") == F.col("_s1")) & (F.col("_k1") == F.col("_s2")), "left").select(*[F.col(f"`{c}`") for c in names], "_spans")
    at = names.index("text")

    def remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, found in zip(batch.column("text").to_pylist(), batch.column("_spans").to_pylist(), strict=True):
                if found:
                    raw = text.encode()
                    text = _kept(raw, _to_characters(raw, merged(found))).decode()
                texts.append(text)
            columns = [batch.column(c) for c in names]
            columns[at] = pa.array(texts, pa.string())
            yield pa.RecordBatch.from_arrays(columns, names)

    out = met.mapInArrow(tidy(remove), docs.schema)
    return out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in names else out
