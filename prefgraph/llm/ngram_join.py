"""Self-join of documents on the Jaccard similarity of their word shingles, by prefixes under several global orders.

A document's set is its distinct 5-word shingles, by 64-bit hashes. Two sets whose similarity reaches the threshold share a shingle of
their prefixes under any order of all shingles. Three orders are used: by a corpus-wide frequency level, then a hash; by another hash
alone; and by frequency level, then a third hash. Frequent shingles come last in the first and third, so a passage that many documents
share makes candidates of those only of which it is the greater part.

1. Frequency levels: a sketch over all documents, its counters bounded (any fixed function of a shingle gives an order, so the sketch's
   collisions cost nothing but selectivity).
2. Documents of equal sets are one class, and classes of about one size and of one least shingle (by another hash, without the most frequent ones)
   are one kin: near copies mostly are, and a shingle that all of them have is one kin's, not one of many pairs. Under the first order
   the prefixes are longer by EXTRA percent, so that two similar sets share not one shingle of them but a computable number. Shingles of few
   kins give pairs with counts; a pair stays if its count, and the shingles of many kins that both have, reach that number for any
   two of their classes. Shingles of many kins join only those kins that have enough of them. What stays connects kins to
   candidate groups; a kin that is in none is one by itself.
3. Within a candidate group pairs are taken by shingle (in groups of more than a few members by prefixes under the group's own order, the
   shingles of fewest members first) and must pass size and the prefixes of all three orders before their sets are compared. Pairs
   already connected by verified links are not compared again: they cannot change a component.
4. Groups too large for one task are dealt into parts, and each pair of parts is a task of its own: any two members meet in one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, group_batches, materialize, mix, partitions_for, prefix_sums, release, row_blocks, span_hash, text_buffers, text_key, tidy
from .components import components

SHINGLE = 5
PERCENT = 75
BLOCK = 1 << 19
BATCH_ROWS = 2500  # documents whose prefixes a map task combines at once
SKETCH_BITS, MOST_BITS, SKETCH_CHUNK = 20, 24, 1 << 14
DOCS_A_SKETCH = 300_000  # documents from which the sketch has more counters
DOCS_A_BUCKET = 4000
EXTRA = 5  # percent of a set by which prefixes under the first order are longer when groups are sought
FEW = 16  # kins of a shingle up to which its pairs are counted
ABOVE = 6  # levels by which a shingle is more frequent than most counters and no kin's least one
SIZES = 12  # steps of a kin's sizes in a doubling
LARGE = 2_000_000  # shingles that one task compares; a candidate group beyond them is dealt out by pairs of its parts
TOGETHER = 24  # members of a group from which one meets all its partners at once
ENTRIES = 1 << 22  # shingles of partners that it meets at once
_U = np.uint64
_LOW = np.arange(256, dtype=np.uint8)
_LOW[65:91] += 32
_BLANK = np.zeros(256, bool)
_BLANK[[32, *range(9, 14)]] = True
_SEEDS = (_U(0x243F6A8885A308D3), _U(0x13198A2E03707344), _U(0xA4093822299F31D0))
_PLACE = [_U(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD)]


def shingle_sets(raw: np.ndarray, bounds: np.ndarray) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; a text of fewer words than a shingle has one for all of them, or none."""
    none = np.empty(0, _U)
    if not len(raw):
        return [none] * (len(bounds) - 1)
    low = _LOW[raw]
    word = ~_BLANK[low]
    first = bounds[:-1][np.diff(bounds) > 0]
    begins = word.copy()
    begins[1:] &= ~word[:-1]
    begins[first] = word[first]
    last = bounds[1:][np.diff(bounds) > 0] - 1
    stops = word.copy()
    stops[:-1] &= ~word[1:]
    stops[last] = word[last]
    at, to = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    hashes = span_hash(prefix_sums(low), at, to)
    cuts = np.searchsorted(at, bounds)
    out = []
    with np.errstate(over="ignore"):
        full = np.zeros(max(0, len(hashes) - SHINGLE + 1), _U)
        for j in range(SHINGLE if len(full) else 0):
            full += hashes[j : j + len(full)] * _PLACE[j]
        full = mix(full)
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            if b - a >= SHINGLE:
                s = np.sort(full[a : b - SHINGLE + 1])
                out.append(s[np.r_[True, s[1:] != s[:-1]]] if len(s) > 1 else s)
            elif b > a:
                h = _U(b - a)
                for j in range(b - a):
                    h = h + hashes[a + j] * _PLACE[j]
                out.append(mix(np.array([h], _U) ^ _U(0x5851F42D4C957F2D)))
            else:
                out.append(none)
    return out


def _sets_of(column: pa.Array) -> Iterator[tuple[int, list[np.ndarray]]]:
    """(number of the first row, sets) of blocks of a text column."""
    raw, bounds = text_buffers(column)
    for i, j in row_blocks(bounds, BLOCK):
        yield i, shingle_sets(raw[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i])


def prefix_length(n: int, percent: int = PERCENT) -> int:
    return n - -(-percent * n // 100) + 1


def linked(a: np.ndarray, b: np.ndarray, percent: int = PERCENT) -> bool:
    """Whether 100 * |a and b| >= percent * |a or b| for sorted sets."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a) or 100 * len(a) < percent * len(b):
        return False
    at = np.searchsorted(b, a)
    both = int(np.count_nonzero(b[np.minimum(at, len(b) - 1)] == a))
    return 100 * both >= percent * (len(a) + len(b) - both)


class Orders:
    """The global orders of shingles and the prefixes under them."""

    def __init__(self, levels: np.ndarray, percent: int = PERCENT) -> None:
        self.levels, self.percent, self.shift = levels, percent, _U(65 - len(levels).bit_length())
        self.frequent = np.median(levels[levels > 0]) + ABOVE if levels.any() else 0

    def level(self, s: np.ndarray) -> np.ndarray:
        return self.levels[(s >> self.shift).astype(np.int64)]

    def prefix(self, s: np.ndarray, order: int, extra: int = 0, level: np.ndarray | None = None) -> np.ndarray:
        key = mix(s ^ _SEEDS[order])
        if order != 1:
            key = (key >> _U(8)) | ((self.level(s) if level is None else level).astype(_U) << _U(56))
        p = prefix_length(len(s), self.percent) + extra * len(s) // 100
        return s if p >= len(s) else np.sort(s[np.argpartition(key, p - 1)[:p]])

    def kin(self, s: np.ndarray, level: np.ndarray, other: int) -> int:
        """The kin of a set; other, where all its shingles are frequent."""
        rare = s[level <= self.frequent]
        if not len(rare):
            return other
        with np.errstate(over="ignore"):
            least = (rare * _PLACE[2]).min() + _U(int(np.log2(len(s)) * SIZES)) * _PLACE[0]
        return int(mix(np.array([least], _U))[0].view(np.int64))


def _share(a: np.ndarray, b: np.ndarray) -> bool:
    if len(a) > len(b):
        a, b = b, a
    return bool((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).any())


def sketch_bits(rows: int) -> int:
    """Counters follow the documents, up to 2^MOST_BITS (16 MB of levels): with too many shingles to a counter, rare ones cannot be told from common ones."""
    return min(MOST_BITS, max(SKETCH_BITS, SKETCH_BITS + (rows // DOCS_A_SKETCH).bit_length()))


def frequency_levels(docs: DataFrame, bits: int = SKETCH_BITS) -> np.ndarray:
    """The logarithms of a sketch of shingle counts over all documents: 2^bits counters, of which a task tells those above 0."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << bits, np.uint32)
        for batch in batches:
            for _, sets in _sets_of(batch.column("text")):
                if sets and len(s := np.concatenate(sets)):
                    np.add.at(total, (s >> _U(64 - bits)).astype(np.int64), np.uint32(1))
        chunk, data = [], []
        for k, part in enumerate(total.reshape(-1, SKETCH_CHUNK)):
            at = np.flatnonzero(part)
            if len(at):
                chunk.append(k)
                data.append(at.astype("<u2").tobytes() + part[at].astype("<u4").tobytes())
        if chunk:
            yield pa.RecordBatch.from_arrays([pa.array(chunk, pa.int32()), pa.array(data, pa.binary())], ["chunk", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for chunk, data in zip(batch.column("chunk").to_pylist(), batch.column("counts"), strict=True):
                data = data.as_py()
                n = len(data) // 6
                total = sums.setdefault(chunk, np.zeros(SKETCH_CHUNK, np.int64))
                total[np.frombuffer(data, "<u2", n)] += np.frombuffer(data, "<u4", n, 2 * n)
        level = {k: np.floor(np.log2(v + 1)).astype(np.uint8).tobytes() for k, v in sums.items()}
        yield pa.RecordBatch.from_arrays([pa.array(list(level), pa.int32()), pa.array(list(level.values()), pa.binary())], ["chunk", "levels"])

    parts = docs.select(F.col("text").alias("text")).mapInArrow(tidy(count), "chunk int, counts binary").repartition("chunk").mapInArrow(tidy(add), "chunk int, levels binary").collect()
    levels = np.zeros(1 << bits, np.uint8)
    for r in parts:
        levels[r.chunk * SKETCH_CHUNK : (r.chunk + 1) * SKETCH_CHUNK] = np.frombuffer(r.levels, np.uint8)
    return levels


_FOUND = "kind int, doc_id long, t1 long, t2 long, n long, c1 long, c2 long, kin long, bucket int, data binary"
_FIELDS = (("kind", pa.int32()), ("doc_id", pa.int64()), ("t1", pa.int64()), ("t2", pa.int64()), ("n", pa.int64()), ("c1", pa.int64()), ("c2", pa.int64()), ("kin", pa.int64()), ("bucket", pa.int32()), ("data", pa.binary()))


def _rows(**given: list | np.ndarray | pa.Array) -> pa.RecordBatch:
    n = len(next(iter(given.values())))
    return pa.RecordBatch.from_arrays([given[k].cast(t) if isinstance(given.get(k), pa.Array) else pa.array(given[k], t) if k in given else pa.nulls(n, t) for k, t in _FIELDS], [k for k, _ in _FIELDS])


def _class_of(s: np.ndarray) -> tuple[int, int]:
    """Two independent hashes of a set."""
    with np.errstate(over="ignore"):
        one = mix(np.array([s.sum(), (s * _PLACE[1] ^ (s >> _U(31))).sum()], _U) + _U(len(s)))
    return int(one[0].view(np.int64)), int(one[1].view(np.int64))


def describe(docs: DataFrame, levels: np.ndarray, buckets: int, percent: int) -> DataFrame:
    """Rows of three kinds: 0, a document with the keys of its text and of its class and its kin; 1, first-order prefix shingles by bucket, each
    with a kin; 2, a shingle of many kins (t1, its node) with one of them (t2)."""
    orders = Orders(levels, percent)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(i, BATCH_ROWS) for b in batches for i in range(0, b.num_rows, BATCH_ROWS)):
            n, c1, c2, kin, seen, shingles, owner = [], [], [], [], {}, [], []
            for _, sets in _sets_of(batch.column("text")):
                for s in sets:
                    a, b = _class_of(s) if len(s) else (0, 0)
                    n.append(len(s))
                    c1.append(a)
                    c2.append(b)
                    if len(s) and (a, b) not in seen:
                        level = orders.level(s)
                        seen[a, b] = orders.kin(s, level, a)
                        shingles.append(orders.prefix(s, 0, EXTRA, level))
                        owner.append(np.full(len(shingles[-1]), seen[a, b], np.int64))
                    kin.append(seen[a, b] if len(s) else 0)
            yield _rows(kind=[0] * len(n), doc_id=batch.column("doc_id"), t1=batch.column("t1"), t2=batch.column("t2"), n=n, c1=c1, c2=c2, kin=kin)
            if not shingles:
                continue
            s, o = np.concatenate(shingles), np.concatenate(owner)
            bucket = (s % _U(buckets)).astype(np.int64)
            short = (s >> _U(32)).astype(np.uint32)
            by = np.lexsort((o, bucket.astype(_U) << _U(32) | short))
            s, o, bucket, short = s[by], o[by], bucket[by], short[by]
            once = np.r_[True, (o[1:] != o[:-1]) | (s[1:] != s[:-1])]
            s, o, bucket, short = s[once], o[once], bucket[once], short[once]
            firsts = np.flatnonzero(np.r_[True, (short[1:] != short[:-1]) | (bucket[1:] != bucket[:-1])])
            times = np.diff(np.r_[firsts, len(short)])
            many = np.repeat(times > FEW, times)
            if many.any():  # known as shared by many here: its kins are told at once, and one entry goes on
                yield _rows(kind=[2] * int(many.sum()), t1=_node(bucket[many], short[many]), t2=o[many])
                stay = ~many
                stay[firsts] = True
                s, o, bucket, short, many = s[stay], o[stay], bucket[stay], short[stay], many[stay]
            cuts = np.searchsorted(bucket, np.arange(buckets + 1))
            some = np.flatnonzero(np.diff(cuts))
            data = [short[i:j].tobytes() + o[i:j].astype("<i8").tobytes() + many[i:j].tobytes() for i, j in zip(cuts[some].tolist(), cuts[some + 1].tolist(), strict=True)]
            yield _rows(kind=[1] * len(some), bucket=some, data=data)

    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *text_key(F.col("text")), F.col("text").alias("text"))
    return materialize(keyed.mapInArrow(tidy(find), _FOUND), "shingles")


def _node(bucket: np.ndarray, short: np.ndarray) -> np.ndarray:
    """A shingle as a node of the graph of kins."""
    with np.errstate(over="ignore"):
        return mix((bucket.astype(_U) << _U(32) | short.astype(_U)) ^ _PLACE[4]).view(np.int64)


_SHARED = (("a", pa.int64()), ("b", pa.int64()), ("n", pa.int64()))


def _bucket_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From the entries of a bucket: pairs of kins (a < b) with the number n of shingles they share; for shingles of more than FEW
    kins (node, kin) with n = 0. Shingles meet by 32 bits of their hashes: collisions only add to counts."""
    for table in group_batches(batches, "bucket", 1):
        for number in np.unique(table.column("bucket").to_numpy()):
            parts = table.filter(pa.compute.equal(table.column("bucket"), int(number))).column("data").to_pylist()
            sizes = [len(d) // 13 for d in parts]
            s = np.concatenate([np.frombuffer(d, "<u4", k) for d, k in zip(parts, sizes, strict=True)])
            o = np.concatenate([np.frombuffer(d, "<i8", k, 4 * k) for d, k in zip(parts, sizes, strict=True)])
            told = np.concatenate([np.frombuffer(d, bool, k, 12 * k) for d, k in zip(parts, sizes, strict=True)])
            del parts
            by = np.lexsort((o, s))
            s, o, told = s[by], o[by], told[by]
            once = np.r_[True, (s[1:] != s[:-1]) | (o[1:] != o[:-1])]  # a kin comes from several batches
            told = np.logical_or.reduceat(told, np.flatnonzero(once))
            s, o = s[once], o[once]
            firsts = np.flatnonzero(np.r_[True, s[1:] != s[:-1]])
            times = np.diff(np.r_[firsts, len(s)])
            many = np.repeat((times > FEW) | np.logical_or.reduceat(told, firsts), times)
            tell = many & ~told
            if tell.any():
                yield _shared(_node(np.full(int(tell.sum()), number), s[tell]), o[tell], np.zeros(int(tell.sum()), np.int64))
            group = np.repeat(np.arange(len(firsts)), times)[~many]
            o = o[~many]
            ones, others = [], []
            for step in range(1, FEW):
                same = np.flatnonzero(group[step:] == group[:-step]) if len(group) > step else np.empty(0, np.int64)
                if not len(same):
                    break
                ones.append(o[same])
                others.append(o[same + step])
            if ones:
                a, b = np.concatenate(ones), np.concatenate(others)
                by = np.lexsort((b, a))
                a, b = a[by], b[by]
                at = np.flatnonzero(np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
                yield _shared(a[at], b[at], np.diff(np.r_[at, len(a)]))


def _shared(*columns: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(columns, _SHARED, strict=True)], [k for k, _ in _SHARED])


def _candidate_groups(found: DataFrame, percent: int) -> DataFrame:
    """_n (a kin) and root for kins that may have partners among others.

    Two linked sets share at least ``need`` shingles of their prefixes: the overlap that the threshold asks for, less all that can lie beyond
    the prefix of the set whose prefix ends first in the order. For two kins it is the least over sizes from ``lo`` to ``hi``, and what any two of
    their classes share is no more than what the kins do.
    """
    rows = found.filter("kind = 1").select("bucket", "data").repartition("bucket").sortWithinPartitions("bucket")
    shared = materialize(rows.mapInArrow(tidy(_bucket_pairs), "a long, b long, n long"), "shared")
    release(found.sparkSession)
    many = materialize(shared.filter("n = 0").select("a", "b").unionByName(found.filter("kind = 2").select(F.col("t1").alias("a"), F.col("t2").alias("b"))), "many")
    common = many.groupBy("b").agg(F.count(F.lit(1)).alias("many"))
    sizes = found.filter("kind = 0 and n > 0").groupBy("kin").agg(F.min("n").alias("lo"), F.max("n").alias("hi"))
    sizes = materialize(sizes.join(common, sizes.kin == common.b, "left").select("kin", "lo", "hi", F.coalesce("many", F.lit(0)).alias("many")), "sizes")
    # of the sizes up to hi a smaller one may have one more, by rounding
    beyond = lambda x: F.greatest(F.lit(0), F.ceil(F.col(f"hi{x}") * percent / 100) - 1 - F.floor(F.col(f"hi{x}") * EXTRA / 100) + (F.col(f"lo{x}") < F.col(f"hi{x}")).cast("int"))
    one, two = (sizes.select(F.col("kin").alias(f"_{x}"), F.col("lo").alias(f"lo{x}"), F.col("hi").alias(f"hi{x}"), F.col("many").alias(f"m{x}")) for x in "ab")
    pairs = shared.filter("n > 0").groupBy("a", "b").agg(F.sum("n").alias("n"))
    met = pairs.join(one, F.col("a") == F.col("_a")).join(two, F.col("b") == F.col("_b"))
    need = F.ceil((F.col("loa") + F.col("lob")) * percent / (100 + percent)) - F.greatest(beyond("a"), beyond("b"))
    fits = (F.col("hia") * 100 >= F.col("lob") * percent) & (F.col("hib") * 100 >= F.col("loa") * percent)
    kept = met.filter(fits & (F.col("n") + F.least("ma", "mb") >= need)).select("a", "b")
    # the least need of a set of n, over partners of all sizes; one less for each rounding
    least = F.greatest(F.lit(1), F.floor(F.col("lo") * (EXTRA / 100)) - 3)
    able = materialize(sizes.filter(F.col("many") >= least).select("kin"), "able")
    joined = many.join(able, many.b == able.kin, "left_semi").select("a", "b")
    out = components(materialize(kept.unionByName(joined), "candidates"))
    discard(shared)
    return out.select(F.col("node").alias("_n"), "root")


class _Group:
    """The members of one candidate group and their verified components."""

    def __init__(self, sets: list[np.ndarray], orders: Orders) -> None:
        self.sets, self.orders, self.percent = sets, orders, orders.percent
        self.parent = list(range(len(sets)))
        self.kept: list[list[np.ndarray | None]] = [[None] * 3 for _ in sets]

    def find(self, i: int) -> int:
        while self.parent[i] != i:
            self.parent[i] = self.parent[self.parent[i]]
            i = self.parent[i]
        return i

    def prefix(self, i: int, order: int) -> np.ndarray:
        if self.kept[i][order] is None:
            self.kept[i][order] = self.orders.prefix(self.sets[i], order)
        return self.kept[i][order]

    def candidate(self, i: int, j: int) -> bool:
        """Size and the prefixes of all orders."""
        a, b = len(self.sets[i]), len(self.sets[j])
        return 100 * min(a, b) >= self.percent * max(a, b) and all(_share(self.prefix(i, k), self.prefix(j, k)) for k in (0, 1, 2))

    def solve(self) -> list[int]:
        """The component of each member."""
        return self._few() if len(self.sets) < TOGETHER else self._many()

    def _few(self) -> list[int]:
        """By shingle of the first order, each member in turn against those of other components."""
        k = len(self.sets)
        if k > 1:
            s = np.concatenate([self.prefix(i, 0) for i in range(k)])
            o = np.repeat(np.arange(k), [len(self.prefix(i, 0)) for i in range(k)])
            by = np.argsort(s, kind="stable")
            s, o = s[by], o[by]
            cuts = np.flatnonzero(np.r_[True, s[1:] != s[:-1], True])
            tested: set[tuple[int, int]] = set()
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                members = o[a:b].tolist()
                while len(members) > 1 and len({self.find(m) for m in members}) > 1:
                    i = members.pop(0)
                    for j in members:
                        pair = (i, j) if i < j else (j, i)
                        if self.find(i) != self.find(j) and pair not in tested:
                            tested.add(pair)
                            if self.candidate(i, j) and linked(self.sets[i], self.sets[j], self.percent):
                                self.parent[self.find(j)] = self.find(i)
        return [self.find(i) for i in range(k)]

    def _many(self) -> list[int]:
        """The group's own order, by how many members have a shingle, gives the pairs: its prefixes hold what the fewest members share. A member meets
        all its partners of other components at once; shingles whose members are one component are passed over."""
        k = len(self.sets)
        size = np.array([len(s) for s in self.sets], np.int64)
        start = np.r_[0, np.cumsum(size)]
        all_of, ids, times = np.unique(np.concatenate(self.sets), return_inverse=True, return_counts=True)
        ids, owner = ids.astype(np.int32), np.repeat(np.arange(k, dtype=np.int32), size)
        by = np.lexsort((ids, times.astype(np.int32)[ids], owner))
        length = size + -(self.percent * size) // 100 + 1
        at = by[np.arange(len(ids)) - np.repeat(start[:-1], size) < np.repeat(length, size)]
        at = at[times[ids[at]] > 1]
        of = owner[at]  # in ascending order
        del by
        around = np.argsort(ids[at], kind="stable")
        met = ids[at][around]
        cuts = np.flatnonzero(np.r_[True, met[1:] != met[:-1], True]) if len(met) else np.zeros(1, np.int64)
        holders, width = of[around], np.diff(cuts)
        lists = np.empty(len(at), np.int32)
        lists[around] = np.repeat(np.arange(len(width), dtype=np.int32), width)
        mine = np.searchsorted(of, np.arange(k + 1))
        done = width < 2
        root = np.arange(k)
        rows: list[tuple[np.ndarray, np.ndarray]] = [(start, ids)]
        mark = np.zeros(len(all_of), bool)
        for i in range(k):
            mine_open = lists[mine[i] : mine[i + 1]]
            mine_open = mine_open[~done[mine_open]]
            if not len(mine_open):
                continue
            w = width[mine_open]
            them = holders[_places(cuts[mine_open], w)]
            ends, theirs = np.r_[0, np.cumsum(w)[:-1]], root[them]
            done[mine_open] = np.minimum.reduceat(theirs, ends) == np.maximum.reduceat(theirs, ends)
            js = np.unique(them[(them > i) & (theirs != root[i])])
            js = js[100 * np.minimum(size[js], size[i]) >= self.percent * np.maximum(size[js], size[i])]
            if len(js) and len(rows) == 1:
                for order in (0, 1, 2):
                    held = [self.orders.prefix(s, order) for s in self.sets]
                    rows.append((np.r_[0, np.cumsum([len(h) for h in held])], np.searchsorted(all_of, np.concatenate(held)).astype(np.int32)))
            for part in np.split(js, np.flatnonzero(np.diff(np.cumsum(size[js]) // ENTRIES)) + 1) if len(js) else ():
                for order in (1, 2, 3):
                    part = part[_both(rows[order], i, part, mark) > 0] if len(part) else part
                if not len(part):
                    continue
                both = _both(rows[0], i, part, mark)
                part = part[100 * both >= self.percent * (size[i] + size[part] - both)]
                if len(part):
                    root[np.isin(root, root[part])] = root[i]
        return root.tolist()


def _places(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    return np.repeat(start - np.r_[0, np.cumsum(size)[:-1]], size) + np.arange(size.sum())


def _both(rows: tuple[np.ndarray, np.ndarray], i: int, js: np.ndarray, mark: np.ndarray) -> np.ndarray:
    """How many entries row i and each of the rows js, none of them empty, have in common. mark: all False, before and after."""
    start, ids = rows
    own, n = ids[start[i] : start[i + 1]], start[js + 1] - start[js]
    mark[own] = True
    both = np.add.reduceat(mark[ids[_places(start[js], n)]], np.r_[0, np.cumsum(n)[:-1]], dtype=np.int64)
    mark[own] = False
    return both


def _verify(levels: np.ndarray, percent: int):
    orders = Orders(levels, percent)

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in group_batches(batches, "root", 256):
            table = table.combine_chunks()
            root = table.column("root").to_numpy()
            cuts = np.flatnonzero(np.r_[True, root[1:] != root[:-1], True])
            v, label = table.column("v").to_pylist(), []
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                sets = [s for _, part in _sets_of(table.column("text").slice(a, b - a)) for s in part]
                label += [v[a + i] for i in _Group(sets, orders).solve()]
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()), pa.array(label, pa.int64())], ["a", "b"])

    return verify


def _block_links(members: DataFrame, levels: np.ndarray, percent: int) -> DataFrame | None:
    """Verified links (a, b) of the stored members(root, v, text, parts) of large groups; None without members.

    A group is dealt into so many parts, and a task has two of them: any two members meet in one task at least, so the links give the components.
    """
    if members.isEmpty():
        return None
    part = F.pmod(F.xxhash64("v"), F.col("parts"))
    dealt = members.select("root", "v", "text", part.alias("x"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("y")).filter("x <> y")
    dealt = dealt.select(F.xxhash64("root", F.least("x", "y"), F.greatest("x", "y")).alias("root"), "v", "text")
    return materialize(dealt.repartition("root").sortWithinPartitions("root").mapInArrow(tidy(_verify(levels, percent)), "a long, b long").filter("a <> b").distinct(), "links")


def similar_documents(docs: DataFrame, percent: int = PERCENT, large: int = LARGE) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of docs(doc_id, text).

    component_id is the least doc_id reachable by links. Texts that are null, empty or without words have an empty set and are linked with
    nothing; so is a row of a null doc_id without partners (component_id null). Repeated doc_ids stay rows. Extra columns are
    ignored; an empty table gives no rows. Sets are compared by 64-bit hashes of their shingles.
    """
    spark = docs.sparkSession
    count = docs.count()
    levels = frequency_levels(docs, sketch_bits(count))
    buckets = max(16, partitions_for(count, DOCS_A_BUCKET))
    found = describe(docs, levels, buckets, percent)
    release(spark)
    groups = _candidate_groups(found, percent)
    meta = materialize(found.filter("kind = 0").select("doc_id", "t1", "t2", "n", "c1", "c2", "kin"), "described")
    discard(found)
    release(spark)
    classes = meta.filter("n > 0").groupBy("c1", "c2").agg(F.min("doc_id").alias("id"), F.first("t1").alias("t1"), F.first("t2").alias("t2"), F.first("n").alias("n"), F.first("kin").alias("kin"))
    classes = materialize(classes.withColumn("v", F.monotonically_increasing_id()), "classes")
    wanted = classes.join(groups, classes.kin == groups._n, "left").select(F.coalesce("root", "kin").alias("root"), "v", "t1", "t2", "n")
    sizes = wanted.groupBy("root").agg(F.sum("n").alias("size"), F.count(F.lit(1)).alias("members")).filter("members > 1")
    sizes = materialize(sizes.select(F.col("root").alias("_r"), "size"), "group-sizes")
    parts = F.when(F.col("size") > large, F.greatest(F.lit(2), F.ceil(F.col("size") / max(1, large // 2)))).otherwise(1).cast("int")
    wanted = materialize(wanted.join(sizes, F.col("root") == F.col("_r")).select("root", "v", F.col("t1").alias("w1"), F.col("t2").alias("w2"), parts.alias("parts")), "wanted")
    texts = docs.select(*text_key(F.col("text")), F.col("text").alias("text")).dropDuplicates(["t1", "t2"])
    members = materialize(texts.join(wanted, (F.col("t1") == F.col("w1")) & (F.col("t2") == F.col("w2"))).select("root", "v", "text", "parts"), "members")
    release(spark)
    links = materialize(members.filter("parts = 1").select("root", "v", "text").repartition("root").sortWithinPartitions("root").mapInArrow(tidy(_verify(levels, percent)), "a long, b long"), "links")
    more = _block_links(members.filter("parts > 1"), levels, percent)
    roots = links.select(F.col("a").alias("node"), F.col("b").alias("c")) if more is None else components(links.unionByName(more)).select("node", F.col("root").alias("c"))
    if more is not None:
        roots = roots.filter("node <> c").unionByName(roots.select(F.col("c").alias("node"), "c").distinct())
    named = classes.join(roots, classes.v == F.col("node"), "left").select("c1", "c2", "id", F.coalesce("c", "v").alias("c"))
    named = materialize(named, "named")
    least = materialize(named.groupBy(F.col("c").alias("_c")).agg(F.min("id").alias("component_id")), "least")
    named = materialize(named.join(least, F.col("c") == F.col("_c")).select(F.col("c1").alias("_c1"), F.col("c2").alias("_c2"), "component_id"), "class-components")
    discard(members)
    release(spark)
    met = meta.join(named, (F.col("c1") == F.col("_c1")) & (F.col("c2") == F.col("_c2")) & (F.col("n") > 0), "left")
    return met.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def one_of_each(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """docs with the row of the least doc_id of each component; rows of a null doc_id stay. Rows repeated with one doc_id stay with it."""
    verdict = similar_documents(docs, percent).filter("doc_id = component_id").select(F.col("doc_id").alias("_id")).distinct()
    kept = docs.join(verdict, F.col("doc_id") == F.col("_id"), "left_semi")
    return kept.unionByName(docs.filter(F.col("doc_id").isNull()))


_WORDS = "list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')"
ORACLE = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i : i + {SHINGLE - 1}], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - {SHINGLE - 2}, 2))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.doc_id <> y.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= {PERCENT} * (x.n + y.n - c)),
r AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
m AS (SELECT a, min(b) AS m FROM r GROUP BY 1)
SELECT w.doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, least(w.doc_id, coalesce(m, w.doc_id)) AS component_id FROM w LEFT JOIN n USING (doc_id) LEFT JOIN m ON a = w.doc_id
"""
