"""Benchmark decontamination with DataFrame functions only.

The benchmark's windows (10 consecutive words; a shorter item is one window) become a hash set, whose size is checked before it is put
into the plan, so that every executor has it. A document is one row throughout: its words are split once; a position is a
candidate when the words at both ends of a window are ends of some benchmark window; the hash of a candidate's words is looked up,
and then the words themselves. A benchmark of more windows than the bound is joined with the documents' windows by shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

WINDOW = 10
_NONE = "CAST(array() AS array<struct<at:int,len:int>>)"
MAX_SET = 200_000  # windows in the plan; beyond it, windows of documents are joined by shuffle
_BREAKS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_GAPS = r"\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F"  # _BREAKS for texts whose letters are not in lower case yet
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words_of(text: Column) -> Column:
    """Normalised words: A-Z in lower case, runs of a-z, 0-9 and all beyond ASCII. Null and empty texts have none."""
    return F.filter(F.split(F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER), _BREAKS), lambda w: w != "")


def _cut(words: Column | str, start: Column, length: Column) -> Column:
    return F.slice(words, start, length)


def item_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """gram (words joined by spaces), h, len, first, last, items for each distinct window of benchmark(item_id, text)."""
    words = benchmark.select("item_id", words_of(F.col("text")).alias("w")).filter(F.size("w") > 0)
    length = F.least(F.size("w"), F.lit(window))
    each = words.withColumn("len", length).select("item_id", "len", "w", F.explode(F.sequence(F.lit(1), F.size("w") - length + 1)).alias("i"))
    cut = each.select("item_id", "len", _cut("w", F.col("i"), F.col("len")).alias("s"))
    return cut.groupBy(F.array_join("s", " ").alias("gram"), "len").agg(F.xxhash64(F.first("s")).alias("h"), F.first(F.element_at("s", 1)).alias("first"), F.first(F.element_at("s", -1)).alias("last"), F.collect_set(F.col("item_id").cast("string")).alias("items"))


def _literals(values: set) -> str:
    return ", ".join(str(v) if isinstance(v, int) else "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'" for v in sorted(values))


def _hits(found: list, length_of_window: int) -> str:
    """SQL: the windows of one length in array w that are in the set, as (at, len) with at from 1."""
    at = f"filter(sequence(1, size(w) - {length_of_window - 1}), i -> element_at(w, i) IN ({_literals({r.first for r in found})})"
    if length_of_window > 1:
        at += f" AND element_at(w, i + {length_of_window - 1}) IN ({_literals({r['last'] for r in found})})"
    at += f" AND xxhash64(slice(w, i, {length_of_window})) IN ({_literals({r.h for r in found})})"
    at += f" AND array_join(slice(w, i, {length_of_window}), ' ') IN ({_literals({r.gram for r in found})}))"
    return f"CASE WHEN size(w) >= {length_of_window} THEN transform({at}, i -> named_struct('at', i, 'len', {length_of_window})) ELSE {_NONE} END"


#: Words covered by the union of hits sorted by place: the state is (covered, end of the covered part).
_COVERED = "aggregate(hits, named_struct('n', 0L, 'to', 1), (s, h) -> named_struct('n', s.n + greatest(0, h.at + h.len - greatest(s.to, h.at)), 'to', greatest(s.to, h.at + h.len)), s -> s.n)"


def _once(sql: str) -> Column:
    """An expression on w that computes w once a row, also where the optimizer puts w's definition in its place."""
    return F.expr(f"element_at(transform(array(w), w -> {sql}), 1)")


def with_hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_set: int = MAX_SET) -> DataFrame:
    """docs with the columns w (words) and hits (array of (at, len), sorted) in place of any columns of these names.

    Every row stays; null and repeated ids are no keys. A null or empty text and an empty benchmark give no hits.
    """
    grams = item_windows(benchmark, window)
    bound = grams.select("gram", "len", "h", "first", "last").limit(max_set + 1).collect()
    cut = docs.drop("hits", "w").withColumn("w", words_of(F.col("text")))
    if not bound:
        return cut.withColumn("hits", F.expr(_NONE))
    if len(bound) <= max_set:
        lengths = sorted({r["len"] for r in bound})
        return cut.withColumn("hits", _once("array_sort(concat(" + ", ".join(_hits([r for r in bound if r["len"] == k], k) for k in lengths) + "))"))
    stored = materialize(docs.drop("hits", "w").withColumn("_id", F.monotonically_increasing_id()), "decontam")
    stored = stored.withColumn("w", words_of(F.col("text")))
    every = [f"CASE WHEN size(w) >= {k} THEN transform(sequence(1, size(w) - {k - 1}), i -> named_struct('at', i, 'len', {k})) ELSE {_NONE} END" for k in range(1, window + 1)]
    windows = stored.select("_id", "w", F.explode(F.expr(f"concat({', '.join(every)})")).alias("hit"))
    keyed = windows.select("_id", "hit", F.array_join(F.slice("w", F.col("hit.at"), F.col("hit.len")), " ").alias("gram"), F.col("hit.len").alias("len"))
    found = keyed.join(materialize(grams.select("gram", "len"), "grams"), ["gram", "len"]).groupBy("_id").agg(F.array_sort(F.collect_list("hit")).alias("hits"))
    return stored.join(found, "_id", "left").drop("_id").withColumn("hits", F.coalesce("hits", F.expr(_NONE)))


def remove_documents(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """The rows of docs without any hit, with all their columns."""
    return with_hits(docs, benchmark, window).filter(F.size("hits") == 0).select(*[F.col(f"`{c}`") for c in docs.columns])


def remove_spans(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """docs with the words of hits cut from text, each with what stands between it and the next word; all else of a text stays as it is.

    Raw words and the marks between them alternate, so a text is put together again from those that stay.
    """
    found = with_hits(docs, benchmark, window)
    raw, gaps = F.regexp_extract_all(F.col("text"), F.lit(f"([^{_GAPS}]+)"), F.lit(1)), F.split("text", f"[^{_GAPS}]+", -1)
    inside = "exists(hits, h -> i + 1 >= h.at AND i + 1 < h.at + h.len)"
    left = F.expr(f"element_at(transform(array(_cut), c -> concat(element_at(c.gaps, 1), array_join(transform(c.raw, (x, i) -> CASE WHEN {inside} THEN '' ELSE concat(x, element_at(c.gaps, i + 2)) END), ''))), 1)")
    rows = found.withColumn("_cut", F.when(F.size("hits") > 0, F.struct(raw.alias("raw"), gaps.alias("gaps"))))
    kept = [F.col(f"`{c}`") if c != "text" else F.when(F.size("hits") > 0, left).otherwise(F.col("text")).alias("text") for c in docs.columns]
    return rows.select(*kept)


def report(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_set: int = MAX_SET) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for every row of docs(doc_id, text).

    The rows of a document meet again by a number of its row, after distinct windows got their items: one shuffle of narrow rows.
    """
    found = with_hits(docs.select("doc_id", "text"), benchmark, window, max_set)
    gram = _once("array_distinct(transform(hits, h -> named_struct('gram', array_join(slice(w, h.at, h.len), ' '), 'len', h.len)))")
    each = found.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.size("w").cast("long").alias("n_words"), F.expr(_COVERED).alias("n_hit"), gram.alias("grams"))
    narrow = each.select("row", "doc_id", "n_words", "n_hit", F.explode_outer("grams").alias("g"))
    items = item_windows(benchmark, window).select(F.struct("gram", "len").alias("g"), "items")
    if items.limit(max_set + 1).count() <= max_set:
        items = F.broadcast(items)
    met = narrow.join(items, "g", "left").groupBy("row", "doc_id", "n_words", "n_hit").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    return met.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )


ORACLE = f"""
WITH dw AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS w FROM documents),
iw AS (SELECT item_id, list_filter(string_split_regex(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
ig AS (SELECT DISTINCT item_id, n, array_to_string(w[i : i + n - 1], ' ') AS gram FROM
  (SELECT item_id, w, least(len(w), {WINDOW}) AS n, unnest(range(1, len(w) - least(len(w), {WINDOW}) + 2)) AS i FROM iw WHERE len(w) > 0)),
dg AS (SELECT doc_id, i, n, array_to_string(w[i : i + n - 1], ' ') AS gram FROM
  (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM dw, (SELECT DISTINCT n FROM ig) WHERE len(w) >= n)),
hit AS (SELECT doc_id, i, dg.n, item_id FROM dg JOIN ig USING (gram, n)),
places AS (SELECT doc_id, count(*) AS n_hit FROM (SELECT DISTINCT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY 1),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hit) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN places USING (doc_id) LEFT JOIN its USING (doc_id)
"""
