"""Widest paths: from sets of sources, as witnesses, and for all pairs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DecimalType, FractionalType, IntegralType

from ..functions import path_width as width_of_weights
from ..plans.bsp import run_bsp
from ..plans.storage import number, scratch, store
from .graph import PrefGraph, ranked_weights, two_way

FW_LIMIT = 3000  # vertices of which one task may hold the matrix of widths


def path_width(spark, path: list, g: PrefGraph):
    """The width of a path of ids; None if an edge is missing or there is none."""
    steps = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(zip(path[:-1], path[1:], strict=True))], "i int, src long, dst long")
    widths = steps.join(g.edges, ["src", "dst"], "left").agg(F.collect_list(F.coalesce("w", F.lit(-1))).alias("ws"))
    return widths.select(width_of_weights(F.transform("ws", lambda x: F.when(x >= 0, x))).alias("x")).first().x


def _top(edges: DataFrame):
    """A width that no edge exceeds, in the type of the weights."""
    kind = edges.schema["w"].dataType
    if isinstance(kind, DecimalType):
        return F.lit("9" * (kind.precision - kind.scale)).cast(kind)
    return F.lit(float("inf")).cast(kind) if isinstance(kind, FractionalType) else F.lit(1 << 62).cast("long")


def widest_from(g: PrefGraph, sources: DataFrame, direction: str = "out", log: list | None = None) -> DataFrame:
    """(source, id, width): for each of sources(id) the width of a widest path to (direction "out") or from ("in") every vertex it is connected with."""
    edges = (g if direction == "out" else g.reversed()).edges
    start = sources.select(F.col("id").alias("source"), "id", _top(edges).alias("value"))
    done = run_bsp(start, edges, ["source"], lambda v, w: F.least(v, w), F.max, lambda new, old: new > old, log=log)
    return done.filter("id <> source").select("source", "id", F.col("value").alias("width"))


def widest_both(g: PrefGraph, sources: DataFrame, log: list | None = None) -> DataFrame:
    """(source, id, out, back): widths from each of sources(id) to a vertex and back, 0 without a path; both directions in one loop of supersteps."""
    start = sources.select(F.explode(F.array(F.lit("f"), F.lit("b"))).alias("direction"), F.col("id").alias("source"), "id", _top(g.edges).alias("value"))
    done = run_bsp(start, two_way(g.edges), ["direction", "source"], lambda v, w: F.least(v, w), F.max, lambda new, old: new > old, log=log)
    width = lambda d: F.coalesce(F.max(F.when(F.col("direction") == d, F.col("value"))), F.lit(0))
    return done.filter("id <> source").groupBy("source", "id").agg(width("f").alias("out"), width("b").alias("back"))


def wide_path_exists(g: PrefGraph, a: int, b: int, w, strict: bool = False) -> bool:
    """Whether a path of width >= w (> w) leads from a to b: frontiers over the edges that are wide enough, until b is met."""
    edges, seen = g.at_least(w, strict).edges, g.vertices.filter(F.col("id") == a).select("id")
    front = seen
    while not front.isEmpty():
        if not front.filter(F.col("id") == b).isEmpty():
            return True
        front = store(front.join(edges, F.col("id") == F.col("src")).select(F.col("dst").alias("id")).distinct().join(seen, "id", "left_anti"), "front")
        seen = store(seen.unionByName(front), "seen")
    return False


def widest_by_threshold(g: PrefGraph, a: int, b: int):
    """The width of a widest path by binary search over the distinct weights; None without a path. The weights stay a numbered table."""
    ranks = store(number(g.edges.select("w").distinct(), [F.col("w")], "rank"), "ranks", n=F.count(F.lit(1)))
    low, high, best = 1, ranks.told["n"], None
    while low <= high:
        mid = (low + high) // 2
        w = ranks.filter(F.col("rank") == mid).first().w
        if wide_path_exists(g, a, b, w):
            best, low = w, mid + 1
        else:
            high = mid - 1
    return best


def widest_path(g: PrefGraph, a: int, b: int) -> list[int] | None:
    """A widest path from a to b, fewest edges first: breadth-first over edges of at least its width, traced back."""
    width = widest_by_threshold(g, a, b)
    if width is None:
        return None
    edges = g.at_least(width).edges
    seen = store(g.vertices.filter(F.col("id") == a).select("id", F.lit(None).cast("long").alias("before")), "trace")
    front = seen
    while seen.filter(F.col("id") == b).isEmpty():
        reached = front.select(F.col("id").alias("src")).join(edges, "src").groupBy(F.col("dst").alias("id")).agg(F.min("src").alias("before"))
        front = store(reached.join(seen.select("id"), "id", "left_anti"), "trace")
        seen = store(seen.unionByName(front), "trace")
    path, at = [b], b
    while at != a:
        at = seen.filter(F.col("id") == at).first().before
        path.append(at)
    return path[::-1]


def closure_matrix(m: np.ndarray) -> np.ndarray:
    """Max-min closure of a square matrix of widths (0: no edge), one middle vertex at a time.

    Widths take the least type that holds them, and rows go in strips that stay in a core's cache.
    """
    kind = next(t for t in (np.int16, np.int32, np.int64) if not m.size or m.max() <= np.iinfo(t).max)
    p = m.astype(kind)
    strip = max(1, (1 << 18) // max(1, p.itemsize * len(p)))
    held = np.empty((strip, len(p)), kind)
    for k in range(len(p)):
        row, column = p[k].copy(), p[:, k].copy()
        for i in range(0, len(p), strip):
            part = p[i : i + strip]
            np.minimum(column[i : i + strip, None], row, out=held[: len(part)])
            np.maximum(part, held[: len(part)], out=part)
    return p.astype(m.dtype)


def _floyd_warshall(g: PrefGraph) -> DataFrame:
    m = g.vertices.count()
    if m > FW_LIMIT:
        raise ValueError(f"{m} vertices: the sequential closure holds all pairs in one task, at most {FW_LIMIT} vertices; take method='squaring' or 'blocked'")

    def close(rows: pd.DataFrame) -> pd.DataFrame:
        ids = np.unique(np.r_[rows.src, rows.dst])
        p = np.zeros((len(ids), len(ids)), np.int64)
        p[np.searchsorted(ids, rows.src), np.searchsorted(ids, rows.dst)] = rows.w
        p = closure_matrix(p)
        a, b = np.nonzero(p)
        keep = a != b
        return pd.DataFrame({"a": ids[a[keep]], "b": ids[b[keep]], "width": p[a[keep], b[keep]]})

    return g.edges.withColumn("all", F.lit(1)).groupBy("all").applyInPandas(close, "a long, b long, width long")


def _squaring(g: PrefGraph) -> DataFrame:
    """Repeated composition of the widths with themselves: after i rounds all paths of up to 2^i edges."""
    p = store(g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("w").alias("width")), "widths")
    before = None
    while True:
        left, right = p.select("a", F.col("b").alias("k"), F.col("width").alias("x")), p.select(F.col("a").alias("k"), "b", F.col("width").alias("y"))
        longer = left.join(right, "k").filter("a <> b").select("a", "b", F.least("x", "y").alias("width"))
        p = store(p.unionByName(longer).groupBy("a", "b").agg(F.max("width").alias("width")), "widths")
        now = p.agg(F.count(F.lit(1)), F.sum("width")).first()
        if now == before:
            return p
        before = now


def _blocked(g: PrefGraph, size: int = 256) -> DataFrame:
    """Closure of a dense matrix in square blocks, each one row of a table, in three phases for each block on the diagonal.

    The diagonal block is closed, then the blocks in its row and column, then every block (i, j) takes paths by (i, k) and (k, j). A phase
    moves (m / size)^2 blocks at most, and a task holds three. What is broadcast to a phase is one block.
    """
    blocks = g.edges.groupBy(F.floor(F.col("src") / size).cast("int").alias("i"), F.floor(F.col("dst") / size).cast("int").alias("j"))
    form = lambda b: np.frombuffer(b, np.int64).reshape(size, size)
    kind = "i int, j int, x binary"

    def dense(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        x = np.zeros((size, size), np.int64)
        x[rows.src % size, rows.dst % size] = rows.w
        return pd.DataFrame({"i": [key[0]], "j": [key[1]], "x": [x.tobytes()]})

    def extend(out: np.ndarray, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        for k in range(size):
            np.maximum(out, np.minimum(one[:, k, None], two[None, k, :]), out=out)
        return out

    def panels(middle: bytes, k: int):
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            closed = form(middle)
            for batch in batches:
                done = [extend(form(x).copy(), closed, form(x)) if i == k else extend(form(x).copy(), form(x), closed) for i, x in zip(batch.i, batch.x, strict=True)]
                yield pd.DataFrame({"i": batch.i, "j": batch.j, "x": [x.tobytes() for x in done]})

        return run

    def through(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            made = [extend(np.zeros((size, size), np.int64) if x is None else form(x).copy(), form(one), form(two)) if one is not None and two is not None else form(x) for x, one, two in zip(batch.x, batch.one, batch.two, strict=True)]
            yield pd.DataFrame({"i": batch.i, "j": batch.j, "x": [x.tobytes() for x in made]})

    p = store(blocks.applyInPandas(dense, kind), "blocks", last=F.max(F.greatest("i", "j")))
    for k in range(1 + (p.told["last"] if p.told["last"] is not None else -1)):
        with scratch() as keep:
            row = p.filter((F.col("i") == k) & (F.col("j") == k)).first()
            if row is not None:
                middle = closure_matrix(form(row.x)).tobytes()
                sides = store(p.filter(((F.col("i") == k) | (F.col("j") == k)) & (F.col("i") != F.col("j"))).mapInPandas(panels(middle, k), kind), "blocks")
                sides = sides.unionByName(p.sparkSession.createDataFrame([(k, k, middle)], kind))
            else:
                sides = p.filter((F.col("i") == k) | (F.col("j") == k))
            into, out = sides.filter(f"j = {k} and i <> {k}").select("i", F.col("x").alias("one")), sides.filter(f"i = {k} and j <> {k}").select("j", F.col("x").alias("two"))
            grid = _grid(into.select("i"), out.select("j"))
            rest = p.filter(f"i <> {k} and j <> {k}").join(grid, ["i", "j"], "full_outer").join(into, "i", "left").join(out, "j", "left").select("i", "j", "x", "one", "two")
            p = store(rest.mapInPandas(through, kind).unionByName(sides), "blocks")
            keep.append(p)

    def sparse(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for i, j, x in zip(batch.i, batch.j, batch.x, strict=True):
                m = form(x)
                a, b = np.nonzero(m)
                keep = a + i * size != b + j * size
                yield pd.DataFrame({"a": a[keep] + i * size, "b": b[keep] + j * size, "width": m[a[keep], b[keep]]})

    return p.mapInPandas(sparse, "a long, b long, width long")


def _grid(into: DataFrame, out: DataFrame) -> DataFrame:
    """(i, j) of the blocks that paths by the middle block may fill: one array of the columns, of at most m / size numbers, to each row."""
    columns = out.agg(F.collect_list("j").alias("_js"))
    return into.join(F.broadcast(columns), F.lit(True)).select("i", F.explode("_js").alias("j"))


def all_pairs_widest(g: PrefGraph, method: str = "squaring") -> DataFrame:
    """(a, b, width) of all connected ordered pairs. Methods: fw (one task), squaring, blocked, vertex (every vertex a source).

    Weights are whole or real numbers above 0. The matrices of fw and blocked hold ranks of weights where these are not whole numbers.
    """
    if method == "vertex":
        return widest_from(g, g.vertices.select("id")).select(F.col("source").alias("a"), F.col("id").alias("b"), "width")
    if method == "squaring":
        return _squaring(g)
    close = {"fw": _floyd_warshall, "blocked": _blocked}[method]
    if isinstance(g.edges.schema["w"].dataType, IntegralType):
        return close(g)
    edges, ranks = ranked_weights(g.edges)
    found = close(PrefGraph(g.vertices, edges))
    return found.join(ranks.select(F.col("rank").alias("width"), "w"), "width").select("a", "b", F.col("w").alias("width"))
