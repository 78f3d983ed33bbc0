"""Alternatives of the same rank on every ballot, as one; and profiles of so few of these that one task holds all their margins."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

from ..operators import onetask
from ..operators.graph import PrefGraph
from .storage import PAIRS_A_TASK, small, store

#: What one task takes: ranks (voters times alternatives, 6 bytes each as they come, 2 to 4 then), and alternatives of which it holds a matrix or its closure, which takes their cube.
MATRIX, WHOLE, CLOSURE = 80_000_000, 12_288, 6_144


class Alike:
    """Ballots by their classes of alternatives that every voter ranks alike, each by its least alternative.

    Members of a class have margin 0 to each other and the same margin to any other alternative, so a widest path needs one of them at most, widths
    inside a class are the same in both directions, and members win, stand in the Schwartz set or are covered together.
    """

    def __init__(self, ballots: DataFrame) -> None:
        row = F.sort_array(F.collect_list(F.struct("voter", "rank", "weight")))
        marked = store(ballots.groupBy("alt").agg(F.sha2(F.to_json(row), 256).alias("as")), "marked")
        first = marked.groupBy("as").agg(F.min("alt").alias("first"), F.count(F.lit(1)).alias("size"))
        self.members = store(marked.join(first, "as").select("alt", "first", "size"), "alike", m=F.count(F.when(F.col("alt") == F.col("first"), 1)))
        self.m = self.members.told["m"]
        ones = self.members.filter("alt = first").select("alt", "size")
        self.ballots = store(ballots.join(small(ones, self.m), "alt").select("voter", "alt", "rank", "weight", "size"), "ballots")
        self.voters = self.ballots.select("voter").distinct().count()

    def held(self, most: int = MATRIX) -> bool:
        """Whether one task holds the ranks of all voters."""
        whole = isinstance(self.ballots.schema["weight"].dataType, IntegralType)
        return whole and self.voters * self.m <= most

    def graph(self) -> PrefGraph:
        """The majority graph of the first members. Margins are those of the whole profile; Borda scores count a class once."""
        from ..operators.margins import graph_of

        return graph_of(self.ballots.select("voter", "alt", "rank", "weight"))

    def all_of(self, found: DataFrame) -> DataFrame:
        """found(alt, ...) of first members, for all members."""
        return self.members.select("alt", "first").join(found.withColumnRenamed("alt", "first"), "first").drop("first")

    def gathered(self, make: Callable[[onetask.Profile, pa.Array, np.ndarray], pa.RecordBatch], schema: str) -> DataFrame:
        """What make(profile, alternatives, sizes) gives in one task, where first members stand about in the order of their scores."""
        m, voters = self.m, self.voters

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ranks, weigh, size = np.full((voters, m), np.iinfo(np.int32).max, np.int32), np.zeros(voters, np.int64), np.zeros(m, np.int64)
            listed, below, last = np.zeros(m), np.zeros(m), 0
            seen: dict[str, dict] = {"voter": {}, "alt": {}}
            for batch in batches:
                at = []
                for c, known in seen.items():
                    coded = batch.column(c).dictionary_encode()
                    new = np.array([known.setdefault(x, len(known)) for x in coded.dictionary.to_pylist()], np.int64)
                    at.append(new[coded.indices.to_numpy(zero_copy_only=False)])
                (v, a), rank, weight = at, batch.column("rank").to_numpy(), batch.column("weight").to_numpy()
                ranks[v, a], weigh[v], size[a] = rank, weight, batch.column("size").to_numpy()
                listed += np.bincount(a, weights=weight, minlength=m)
                below += np.bincount(a, weights=weight * rank.astype(float), minlength=m)
                last = max(last, int(rank.max(initial=0)))
            if not seen["alt"]:
                return
            order = np.argsort(below - (last + 1.0) * listed, kind="stable")
            names = pa.array(list(seen["alt"]), batch.schema.field("alt").type)
            yield make(onetask.Profile(onetask.dense_ranks(ranks[:, order]), weigh), names.take(pa.array(order)), size[order])

        rows = self.ballots.select("voter", "alt", F.col("rank").cast("int").alias("rank"), F.col("weight").cast("long").alias("weight"), "size")
        return rows.repartition(1).mapInArrow(run, schema)

    def decide(self, solve: Callable[[onetask.Profile, np.ndarray], dict[str, np.ndarray]], columns: str = "") -> DataFrame:
        """(alt, columns...) of first members, in one task. solve(profile, sizes): ``at``, the places found, and an array for each column."""

        def make(p: onetask.Profile, names: pa.Array, size: np.ndarray) -> pa.RecordBatch:
            found = solve(p, size)
            at = found.pop("at")
            return pa.RecordBatch.from_arrays([names.take(pa.array(at)), *[pa.array(x, pa.int64()) for x in found.values()]], ["alt", *found])

        return self.gathered(make, f"alt {self.ballots.schema['alt'].dataType.simpleString()}{', ' + columns if columns else ''}")

    def uncovered(self) -> DataFrame:
        """(alt): first members that none covers. The ranks of all, in one row, are broadcast to tasks that ask about a share of them each."""
        kind, spark = self.ballots.schema["alt"].dataType.simpleString(), self.ballots.sparkSession

        def make(p: onetask.Profile, names: pa.Array, size: np.ndarray) -> pa.RecordBatch:
            one = pa.ListArray.from_arrays(pa.array([0, len(names)], pa.int32()), names)
            return pa.RecordBatch.from_arrays([pa.array([p.ranks.tobytes()], pa.binary()), pa.array([str(p.ranks.dtype)]), pa.array([p.weight.tobytes()], pa.binary()), one], ["ranks", "type", "weight", "alts"])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for i in range(batch.num_rows):
                    weight, names = np.frombuffer(batch.column("weight")[i].as_py(), np.int64), batch.column("alts")[i].values
                    ranks = np.frombuffer(batch.column("ranks")[i].as_buffer(), batch.column("type")[i].as_py()).reshape(len(weight), -1)
                    asked = np.arange(batch.column("id")[i].as_py(), ranks.shape[1], tasks)
                    yield pa.RecordBatch.from_arrays([names.take(pa.array(onetask.uncovered_of(onetask.Profile(ranks, weight), asked)))], ["alt"])

        tasks = max(8, 2 * spark.sparkContext.defaultParallelism)  # each begins with the sample
        whole = store(self.gathered(make, f"ranks binary, type string, weight binary, alts array<{kind}>"), "profile")
        return spark.range(0, tasks, 1, tasks).join(F.broadcast(whole), F.lit(True)).mapInArrow(run, f"alt {kind}")


def winners(ballots: DataFrame) -> DataFrame:
    """(alt): the winners of the widest-path rule, unlisted alternatives last."""
    from .winners import find_winners

    b = Alike(ballots)
    if b.held():
        return b.all_of(b.decide(lambda p, size: {"at": onetask.undefeated(p)}))
    g = b.graph()
    return b.all_of(g.vertices.join(find_winners(g).winners, "id", "left_semi").select("alt"))


def schwartz_set(ballots: DataFrame) -> DataFrame:
    """(alt): the union of the components without an edge from outside."""
    from ..operators import components

    b = Alike(ballots)
    if b.held():
        return b.all_of(b.decide(lambda p, size: {"at": np.concatenate(onetask.sources(p))}))
    g = b.graph()
    return b.all_of(g.vertices.join(components.schwartz_set(g), "id", "left_semi").select("alt"))


def uncovered_set(ballots: DataFrame) -> DataFrame:
    """(alt): the alternatives that none covers."""
    from ..operators import components

    b = Alike(ballots)
    if b.held():
        return b.all_of(b.decide(lambda p, size: {"at": onetask.uncovered(onetask.margin_matrix(p))}) if b.m <= WHOLE else b.uncovered())
    g = b.graph()
    return b.all_of(g.vertices.join(components.uncovered_set(g), "id", "left_semi").select("alt"))


def ranking(ballots: DataFrame) -> DataFrame:
    """(alt, beaten_by, beats, rnk), as rule.ranking gives them for the whole graph."""
    from ..operators import paths, rule

    b = Alike(ballots)
    if b.held() and b.m <= CLOSURE:

        def solve(p: onetask.Profile, size: np.ndarray) -> dict[str, np.ndarray]:
            beaten, beats = onetask.beat_counts(onetask.margin_matrix(p), size)
            return {"at": np.arange(p.n), "beaten_by": beaten, "beats": beats}

        each = store(b.all_of(b.decide(solve, "beaten_by long, beats long")), "counts")
        return rule.ranked(each)
    g = b.graph()
    one = b.members.filter("alt = first").join(g.vertices.select("alt", "id"), "alt").select("id", "size")
    return rule.ranked(b.all_of(rule.counted(paths.all_pairs_widest(g, "blocked"), one).join(g.vertices, "id").select("alt", "beaten_by", "beats")))


def _members_of(b: Alike) -> DataFrame:
    """(first, alts): the members of each class."""
    return store(b.members.groupBy("first").agg(F.sort_array(F.collect_list("alt")).alias("alts")), "members")


def _spread(df: DataFrame, rows: int) -> DataFrame:
    """Rows that each make many, in as many tasks as they ask for."""
    return df.repartition(max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(4096, rows // PAIRS_A_TASK)))


def margins_by_group(ballots: DataFrame, group: str) -> DataFrame:
    """(group, a, b, margin), as margins.by_group gives them with unlisted alternatives last: margins of classes, spread over their members.

    All members of a class are listed at the same levels; their margins to each other are 0. No pair of members is moved between tasks.
    """
    from ..operators.margins import by_group

    b = Alike(ballots.select("voter", "alt", "rank", "weight"))
    of = ballots.select("voter", group).distinct()
    told = store(b.ballots.join(of, "voter").select("voter", "alt", "rank", "weight", group), "ballots")
    levels = told.select("alt", group).distinct()
    levels = levels.unionByName(levels.select("alt", F.lit(None).cast(levels.schema[group].dataType).alias(group)).distinct())
    alts = _members_of(b)
    size = b.members.count()
    one, two = (small(alts.select(F.col("first").alias(f"_{x}"), F.col("alts").alias(f"_{x}s")), size) for x in "ab")
    between = _spread(by_group(told, group), 3 * size * size).join(one, F.col("a") == F.col("_a")).join(two, F.col("b") == F.col("_b"))
    each = between.select(group, F.explode("_as").alias("x"), "_bs", "margin").select(group, "x", F.explode("_bs").alias("y"), "margin")
    ahead = F.col("x") < F.col("y")
    each = each.select(group, F.when(ahead, F.col("x")).otherwise(F.col("y")).alias("a"), F.when(ahead, F.col("y")).otherwise(F.col("x")).alias("b"), F.when(ahead, F.col("margin")).otherwise(-F.col("margin")).alias("margin"))
    within = levels.join(small(alts.filter(F.size("alts") > 1), size), F.col("alt") == F.col("first"))
    within = within.select(group, F.explode("alts").alias("a"), "alts").select(group, "a", F.explode("alts").alias("b"), F.lit(0).cast("long").alias("margin")).filter("a < b")
    return each.unionByName(within)


def widest_paths(ballots: DataFrame) -> DataFrame:
    """(a, b, width) of all connected ordered pairs, as paths.all_pairs_widest gives them for the whole graph: widths of classes, spread over their members.

    Two members of a class are joined by a path out of it and back, the widest one over all other classes.
    """
    from ..operators import paths

    b = Alike(ballots)
    g = b.graph()
    found = store(g.named(paths.all_pairs_widest(g, "blocked"), "a", "b"), "widths")
    alts = _members_of(b)
    size = b.members.count()
    one, two = (small(alts.select(F.col("first").alias(f"_{x}"), F.col("alts").alias(f"_{x}s")), size) for x in "ab")
    between = _spread(found, size * size).join(one, F.col("a") == F.col("_a")).join(two, F.col("b") == F.col("_b"))
    between = between.select(F.explode("_as").alias("a"), "_bs", "width").select("a", F.explode("_bs").alias("b"), "width")
    several = alts.filter(F.size("alts") > 1)
    back = found.select(F.col("a").alias("v"), F.col("b").alias("first"), F.col("width").alias("back"))
    round_trip = found.join(small(several.select(F.col("first").alias("a")), size), "a", "left_semi").join(back, (F.col("a") == F.col("first")) & (F.col("b") == F.col("v")))
    round_trip = round_trip.groupBy("first").agg(F.max(F.least("width", "back")).alias("width"))
    within = several.join(round_trip, "first").select(F.explode("alts").alias("a"), "alts", "width").select("a", F.explode("alts").alias("b"), "width").filter("a <> b")
    return between.unionByName(within)
