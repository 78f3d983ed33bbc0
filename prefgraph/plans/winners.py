"""Winner determination without all pairs.

Exact ways that share one table of statuses:

* label passes: every vertex learns the least undecided id that reaches it and that it reaches, with the widths, and these decide losers,
  components and one winner or loser at least in each component without incoming edges;
* pivot passes: the undecided vertex of the least id (the best score) is compared with all others by two single-source searches;
* the finish: all undecided vertices, if few, are compared with all others together.

* one task: a graph of few edges is decided where all of them are (operators/onetask).

``strategy="auto"`` takes one task for a graph that it holds; beyond that, pivots while a pass decides half of the undecided, the finish when few are left; else the closure of a small graph,
the finish if its messages are few enough, or label passes;
``strategy="labels", finish_threshold=0, prune="zero"`` is the plain label method; ``labels=q`` lets a vertex hold q ids in a pass.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import TOP, label_of, pack, width_of
from ..operators.graph import PrefGraph, ranked_weights, two_way
from ..operators.scores import assign_ids
from .bsp import run_bsp
from .storage import discard, scratch, small, store

#: Undecided vertices that are compared with all others at once, if a superstep of that sends at most so many messages.
FEW, MESSAGES = 64, 2_000_000_000
#: Vertices up to which the widths of all pairs are taken in one task where pivots no longer halve the undecided.
CLOSED = 2048
#: Edges up to which one task decides the whole graph: 12 bytes each as they come, and some 50 as it works.
ONE_TASK = 12_000_000
UNKNOWN, WINNER, LOSER = "unknown", "winner", "loser"


@dataclass
class WinnersResult:
    winners: DataFrame  # id
    state: DataFrame  # id, status
    log: list[dict] = field(default_factory=list)

    @property
    def rounds(self) -> int:
        return sum(1 for x in self.log if x["kind"] != "init")

    @property
    def supersteps(self) -> int:
        return sum(x.get("supersteps", 0) for x in self.log)


def initial_status(g: PrefGraph) -> DataFrame:
    """(id, status): a vertex whose heaviest incoming edge outweighs all its outgoing ones loses to that edge's source."""
    into = g.edges.groupBy(F.col("dst").alias("id")).agg(F.max("w").alias("i"))
    out = g.edges.groupBy(F.col("src").alias("id")).agg(F.max("w").alias("o"))
    both = g.vertices.select("id").join(into, "id", "left").join(out, "id", "left")
    return both.select("id", F.when(F.coalesce("i", F.lit(0)) > F.coalesce("o", F.lit(0)), LOSER).otherwise(UNKNOWN).alias("status"))


def init_labels(state: DataFrame) -> DataFrame:
    """(direction, id, value): undecided vertices start with their own id at full width in both directions; others have no label."""
    own = state.filter(F.col("status") == UNKNOWN).select("id", pack(F.col("id").cast("long"), F.lit(TOP)).alias("value"))
    return own.select(F.explode(F.array(F.lit("f"), F.lit("b"))).alias("direction"), "id", "value")


def with_ranks(g: PrefGraph) -> PrefGraph:
    """g with each weight's rank among the distinct weights in its place, unless weights are whole and below TOP already.

    Widths of paths are compared, never added, so only the order of weights matters; ranks fit a packed label for weights of any size or type.
    """
    most, top = g.edges.agg(F.max("w")).first()[0], g.vertices.agg(F.max("id")).first()[0]
    if (top or 0) >= TOP:
        raise ValueError(f"id {top}: label passes take ids below {TOP}")
    if dict(g.edges.dtypes)["w"] in ("int", "bigint", "smallint", "tinyint") and (most or 0) < TOP:
        return PrefGraph(g.vertices, g.edges.withColumn("w", F.col("w").cast("long")))
    return PrefGraph(g.vertices, ranked_weights(g.edges)[0])


def label_pass(state: DataFrame, edges: DataFrame, combiner: bool = True, log: list | None = None, messages: bool = False) -> DataFrame:
    """(id, status, s, ws, t, wt) for every vertex of state; s and t are null where no undecided vertex reaches it or is reached.

    Both directions run in one job a superstep; the least packed value is the least id with its greatest width. Without combiner, messages
    are collected before the minimum is taken (for comparison only). Weights are whole and below TOP (with_ranks).
    """
    least = F.min if combiner else (lambda c: F.array_min(F.collect_list(c)))
    send = lambda v, w: pack(label_of(v), F.least(width_of(v), w))
    done = run_bsp(init_labels(state), two_way(edges.filter("w > 0")), ["direction"], send, least, lambda new, old: new < old, log=log, messages=messages)
    of = lambda d: F.min(F.when(F.col("direction") == d, F.col("value")))
    wide = done.groupBy("id").agg(of("f").alias("f"), of("b").alias("b"))
    met = state.select("id", "status").join(wide, "id", "left")
    return store(met.select("id", "status", label_of(F.col("f")).alias("s"), width_of(F.col("f")).alias("ws"), label_of(F.col("b")).alias("t"), width_of(F.col("b")).alias("wt")), "labels")


def many_labels_pass(state: DataFrame, edges: DataFrame, q: int, log: list | None = None) -> tuple[DataFrame, DataFrame]:
    """((id, direction, label, width) of the q least undecided ids that reach each vertex or are reached, labels as label_pass gives).

    An id among the q least that reach a vertex is among the q least at every vertex on the way, so cutting to q loses no width.
    """
    place = F.row_number().over(Window.partitionBy("direction", "id").orderBy("label"))
    cut = lambda rows: rows.withColumn("_place", place).filter(F.col("_place") <= q).drop("_place")
    own = state.filter(F.col("status") == UNKNOWN).select(F.explode(F.array(F.lit("f"), F.lit("b"))).alias("direction"), F.col("id").alias("label"), "id", F.lit(TOP).cast("long").alias("value"))
    lists = run_bsp(own, two_way(edges.filter("w > 0")), ["direction", "label"], lambda v, w: F.least(v, w), F.max, lambda new, old: new > old, log=log, prune=cut)
    lists = lists.withColumnRenamed("value", "width")
    first = lambda d: F.min_by(F.struct("label", "width"), F.when(F.col("direction") == d, F.col("label")))
    least = lists.groupBy("id").agg(first("f").alias("f"), first("b").alias("b"), F.count(F.when(F.col("direction") == "f", 1)).alias("nf"), F.count(F.when(F.col("direction") == "b", 1)).alias("nb"))
    end = lambda c, n: F.when(F.col(n) > 0, F.col(c))
    met = state.select("id", "status").join(least, "id", "left").select("id", "status", end("f.label", "nf").alias("s"), end("f.width", "nf").alias("ws"), end("b.label", "nb").alias("t"), end("b.width", "nb").alias("wt"))
    return lists, store(met, "labels")


def resolve_lists(lists: DataFrame, q: int) -> DataFrame:
    """(id) of losers seen from lists of q labels: x and v are compared where both of v's lists tell of x, by x or by what they lack up to their ends."""
    ends = lists.groupBy("id").agg(*[F.when(F.count(F.when(F.col("direction") == d, 1)) >= q, F.max(F.when(F.col("direction") == d, F.col("label")))).otherwise(TOP).alias(f"{d}_end") for d in ("f", "b")])
    side = lambda d: lists.filter(F.col("direction") == d).select("id", "label", F.col("width").alias(d))
    pairs = side("f").join(side("b"), ["id", "label"], "full_outer").join(ends, "id").filter("id <> label")
    there, back = F.coalesce("f", F.lit(0)), F.coalesce("b", F.lit(0))
    told = (F.col("f").isNotNull() | (F.col("label") < F.col("f_end"))) & (F.col("b").isNotNull() | (F.col("label") < F.col("b_end")))
    known = pairs.filter(told)
    return known.filter(there > back).select("id").unionByName(known.filter(back > there).select(F.col("label").alias("id")))


def resolve_local(labels: DataFrame) -> DataFrame:
    """(id) of losers seen from a vertex's own labels. A missing label counts as larger than any."""
    s, t = F.coalesce("s", F.lit(TOP)), F.coalesce("t", F.lit(TOP))
    own = labels.filter((s < t) | ((s == t) & (s < TOP) & (F.col("ws") > F.col("wt")))).select("id")
    target = labels.filter(s > t).select(F.col("t").alias("id"))
    source = labels.filter((s == t) & (s < TOP) & (F.col("ws") < F.col("wt"))).select(F.col("s").alias("id"))
    return own.unionByName(target).unionByName(source)


def resolve_incoming(labels: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """((scc) that have an edge from another component, (id) of vertices outside known components that have one)."""
    of = lambda end: labels.select(F.col("id").alias(end), F.coalesce("s", F.lit(TOP)).alias(f"{end}_s"), F.coalesce("t", F.lit(TOP)).alias(f"{end}_t"))
    cross = edges.filter("w > 0").join(of("src"), "src").join(of("dst"), "dst").filter("src_s <> dst_s or src_t <> dst_t")
    known = (F.col("dst_s") == F.col("dst_t")) & (F.col("dst_s") < TOP)
    return cross.filter(known).select(F.col("dst_s").alias("scc")).distinct(), cross.filter(~known).select(F.col("dst").alias("id")).distinct()


def _label_round(g: PrefGraph, state: DataFrame, edges: DataFrame, prune: str, combiner: bool, steps: list, labels: int, messages: bool) -> tuple[DataFrame, DataFrame]:
    with scratch() as keep:
        if labels > 1:
            lists, told = many_labels_pass(state, edges, labels, steps)
            lost, own = resolve_lists(lists, labels), lists.filter("id = label").groupBy("id").agg(F.count(F.lit(1)).alias("own")).filter("own = 2").select("id", F.lit(True).alias("own"))
            first = (F.col("s") == F.col("t")) & F.coalesce("own", F.lit(False))
            told = told.join(own, "id", "left")
        else:
            told = label_pass(state, edges, combiner, steps, messages)
            lost, first = resolve_local(told), (F.col("s") == F.col("id")) & (F.col("t") == F.col("id"))
        dominated, single = resolve_incoming(told, edges)
        dominated = store(dominated, "dominated")
        inside = told.select("id", F.when(F.col("s") == F.col("t"), F.col("s")).alias("scc")).join(dominated, "scc", "left_semi").select("id")
        losers = store(lost.unionByName(single).unionByName(inside).distinct(), "losers")
        marked = told.join(losers.withColumn("lost", F.lit(True)), "id", "left")
        status = F.when(F.col("lost"), LOSER).when(first, WINNER).otherwise(F.col("status"))
        after = _status(marked.select("id", F.when(F.col("status") == UNKNOWN, status).otherwise(F.col("status")).alias("status")))
        keep.append(after)
        if prune != "none":
            dead = inside.select(F.col("id").alias("dst"), F.lit(True).alias("dead"))
            if prune == "drop":
                edges = store(edges.join(dead, "dst", "left_anti").select("src", "dst", "w"), "edges")
            else:
                edges = store(edges.join(dead, "dst", "left").select("src", "dst", F.when(F.col("dead"), 0).otherwise(F.col("w")).cast("long").alias("w")), "edges")
            keep.append(edges)
    return after, edges


def _status(rows: DataFrame) -> DataFrame:
    """(id, status), stored; told: m, how many there are, undecided, how many of them are, and pivot, the least id of these."""
    open_ = F.when(F.col("status") == UNKNOWN, F.col("id"))
    return store(rows, "status", m=F.count(F.lit(1)), undecided=F.count(open_), pivot=F.min(open_))


def closure_pass(g: PrefGraph, state: DataFrame) -> DataFrame:
    """Statuses after the closure of a small graph with many tied vertices."""
    from ..operators.paths import all_pairs_widest
    from ..operators.rule import beats

    lost = beats(all_pairs_widest(g, "fw")).select(F.col("b").alias("id"), F.lit(True).alias("lost")).distinct()
    return _status(state.join(lost, "id", "left").select("id", F.when(F.col("status") != UNKNOWN, F.col("status")).when(F.col("lost"), LOSER).otherwise(WINNER).alias("status")))


def task_pass(g: PrefGraph, state: DataFrame) -> DataFrame:
    """Statuses after one task has taken all edges."""
    from ..operators.onetask import Sparse, undefeated

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [(b.column("src").to_numpy(), b.column("dst").to_numpy(), b.column("w").to_numpy().astype(np.int32)) for b in batches]
        if not held:
            return
        src, dst, w = (np.concatenate(x) for x in zip(*held, strict=True))
        held.clear()
        ids = np.unique(np.r_[np.unique(src), np.unique(dst)])
        src, dst = np.searchsorted(ids, src).astype(np.int32), np.searchsorted(ids, dst).astype(np.int32)
        yield pa.RecordBatch.from_arrays([pa.array(np.delete(ids, undefeated(Sparse(len(ids), src, dst, w))), pa.int64())], ["id"])

    edges = with_ranks(g).edges.filter("w > 0").select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.col("w").cast("int").alias("w"))
    lost = edges.repartition(1).mapInArrow(run, "id long").withColumn("lost", F.lit(True))
    return _status(state.join(lost, "id", "left").select("id", F.when(F.col("lost"), LOSER).otherwise(WINNER).alias("status")))


def finish_exact(g: PrefGraph, state: DataFrame, steps: list | None = None) -> DataFrame:
    """Statuses after comparing every undecided vertex with all others by widths from and to them, in one loop of supersteps."""
    from ..operators.paths import widest_both

    with scratch() as keep:
        asked = store(state.filter(F.col("status") == UNKNOWN).select("id"), "asked")
        lost = widest_both(g, asked, steps).filter("back > out").select(F.col("source").alias("id")).distinct()
        met = state.join(lost.withColumn("lost", F.lit(True)), "id", "left")
        after = _status(met.select("id", F.when(F.col("status") != UNKNOWN, F.col("status")).when(F.col("lost"), LOSER).otherwise(WINNER).alias("status")))
        keep.append(after)
    return after


def pivot_pass(g: PrefGraph, state: DataFrame, steps: list | None = None) -> DataFrame:
    """Statuses after comparing the undecided vertex of the least id with all others: those it beats lose, and it is decided."""
    from ..operators.paths import widest_both

    with scratch() as keep:
        pivot = state.told["pivot"]
        widths = widest_both(g, state.filter(F.col("id") == pivot).select("id"), steps)
        met = state.join(widths.select("id", "out", "back"), "id", "left").select("id", "status", F.coalesce("out", F.lit(0)).alias("out"), F.coalesce("back", F.lit(0)).alias("back"))
        met = store(met, "pivot", beaten=F.count(F.when(F.col("back") > F.col("out"), 1)))
        status = F.when(F.col("id") == pivot, LOSER if met.told["beaten"] else WINNER).when((F.col("status") == UNKNOWN) & (F.col("out") > F.col("back")), LOSER).otherwise(F.col("status"))
        after = _status(met.select("id", status.alias("status")))
        keep.append(after)
    return after


def find_winners(
    g: PrefGraph, strategy: str = "auto", prune: str = "drop", combiner: bool = True, init: bool = True, finish_threshold: int = FEW, max_rounds: int | None = None,
    labels: int = 1, ids: str | None = None, messages: bool = False,
) -> WinnersResult:
    """The winners of the widest-path rule, with a log of rounds, supersteps and undecided vertices. An empty graph has none; without edges all win.

    labels: ids that a vertex holds in a label pass. ids: an order of scores.assign_ids in which vertices take part instead of the graph's own
    (results stay in the graph's ids). messages: the log counts messages, with one more job a superstep.
    """
    if ids is not None:
        return _in_order(g, ids, strategy=strategy, prune=prune, combiner=combiner, init=init, finish_threshold=finish_threshold, max_rounds=max_rounds, labels=labels, messages=messages)
    log: list[dict] = []
    size: list[int] = []

    def edges_of() -> int:
        if not size:
            size.append(getattr(g.edges, "told", {}).get("n") or g.edges.count())
        return size[0]

    def affordable(undecided: int) -> bool:
        return 2 * undecided * edges_of() <= MESSAGES

    with scratch() as keep:
        state = _status(initial_status(g) if init else g.vertices.select("id", F.lit(UNKNOWN).alias("status")))
        edges, left, halved = None, state.told["undecided"], True
        log.append({"kind": "init", "undecided": left})
        while left and (max_rounds is None or len(log) <= max_rounds):
            steps: list = []
            before = state
            if strategy == "auto" and finish_threshold and edges_of() <= ONE_TASK:
                kind, state = "task", task_pass(g, state)
            elif strategy in ("auto", "labels") and left <= finish_threshold and (finish_threshold != FEW or affordable(left)):
                kind, state = "finish", finish_exact(g, state, steps)
            elif strategy == "pivot" or (strategy == "auto" and halved):
                kind, state = "pivot", pivot_pass(g, state, steps)
            elif strategy == "auto" and finish_threshold and state.told["m"] <= CLOSED:
                kind, state = "closure", closure_pass(g, state)
            elif strategy == "auto" and finish_threshold and affordable(left):
                kind, state = "finish", finish_exact(g, state, steps)
            else:
                kind, old = "labels", edges
                edges = with_ranks(g).edges if edges is None else edges
                state, edges = _label_round(g, state, edges, prune, combiner, steps, labels, messages)
                if hasattr(old, "path") and old is not edges:
                    discard(old)
            discard(before)
            now = state.told["undecided"]
            if now >= left:
                raise RuntimeError("a round decided no vertex")
            halved, left = 2 * now <= left, now
            log.append({"kind": kind, "undecided": left, "supersteps": len(steps), "steps": steps})
        keep.append(state)
    return WinnersResult(state.filter(F.col("status") == WINNER).select("id"), state, log)


def _in_order(g: PrefGraph, ids: str, **options) -> WinnersResult:
    """find_winners on g renumbered in another order, with the result in g's ids."""
    with scratch() as keep:
        other = store(assign_ids(g.edges.select(F.col("src").alias("a"), F.col("dst").alias("b"), "w"), g.vertices.select(F.col("id").alias("alt")), ids), "vertices", m=F.count(F.lit(1)))
        of = lambda end: small(other.select(F.col("alt").alias(end), F.col("id").alias(f"_{end}")), other.told["m"])
        edges = store(g.edges.join(of("src"), "src").join(of("dst"), "dst").select(F.col("_src").alias("src"), F.col("_dst").alias("dst"), "w"), "edges")
        found = find_winners(PrefGraph(other.select("alt", "id"), edges), **options)
        state = store(found.state.join(other.select("id", "alt"), "id").select(F.col("alt").alias("id"), "status"), "status")
        keep.append(state)
    return WinnersResult(state.filter(F.col("status") == WINNER).select("id"), state, found.log)


def via_schwartz(g: PrefGraph, method: str = "squaring") -> DataFrame:
    """(id) of the winners by components first: widths only inside the components without incoming edges."""
    from ..operators.components import schwartz_set
    from ..operators.paths import all_pairs_widest
    from ..operators.rule import winners_exact

    inner = g.induced(schwartz_set(g))
    inner = PrefGraph(store(inner.vertices, "schwartz"), store(inner.edges, "schwartz"))
    if inner.edges.isEmpty():
        return inner.vertices.select("id")
    return winners_exact(all_pairs_widest(inner, method), inner.vertices)
