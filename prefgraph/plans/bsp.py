"""Bulk-synchronous rounds as joins: the rows that changed send along edges, messages to one target are combined by a partial
aggregation, and a target changes if the combined message is better."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import BROADCAST_ROWS, dealt, discard, small, store, stored_bytes


def run_bsp(
    state: DataFrame, edges: DataFrame | dict[str, DataFrame], keys: list[str], send: Callable[[Column, Column], Column], combine: Callable[[str], Column], better: Callable[[Column, Column], Column],
    max_steps: int | None = None, log: list | None = None, prune: Callable[[DataFrame], DataFrame] | None = None, messages: bool = False,
) -> DataFrame:
    """Iterate state(keys..., id, value) to a fixpoint; edges(src, dst, w) carry values along.

    keys partition the messages (a source, a direction). edges is one table, or one for each value of the key ``direction``. send makes the
    message from (value, w), combine aggregates messages, better compares (new, old). Rows not in state count as worst. prune drops rows
    of a new state. The result is a stored table; the states before it are deleted.

    A superstep is one job. The rows that changed are broadcast to the edges while they are at most ``BROADCAST_ROWS``, so edges stay where
    they are stored; beyond that, edges are dealt out by their sources once, and only the changed rows move. log gets a row a superstep:
    active and changed rows, bytes of the state, and with messages=True the messages before they are combined.
    """
    at, ways = [*keys, "id"], edges if isinstance(edges, dict) else {None: edges}
    counted = {"moved": F.count(F.when(F.col("moved"), 1))}
    now = store(state.select(*at, "value", F.lit(True).alias("moved")), "state", **counted)
    spread: dict = {}
    step = 0
    while now.told["moved"] and (max_steps is None or step < max_steps):
        step += 1
        if now.told["moved"] > BROADCAST_ROWS and not spread:
            spread = {way: dealt(along, "src") for way, along in ways.items()}
        sent, after = superstep(now, spread if now.told["moved"] > BROADCAST_ROWS else ways, keys, send, combine, better)
        n_messages = sent.count() if messages else None
        after = store(after if prune is None else prune(after), "state", **counted)
        if log is not None:
            log.append({"step": step, "active": now.told["moved"], "changed": after.told["moved"], "state_bytes": stored_bytes(after), "messages": n_messages})
        discard(now)
        now = after
    for along in spread.values():
        along.unpersist()
    return now.drop("moved")


def superstep(now: DataFrame, ways: dict[str | None, DataFrame], keys: list[str], send: Callable[[Column, Column], Column], combine: Callable[[str], Column], better: Callable[[Column, Column], Column]) -> tuple[DataFrame, DataFrame]:
    """(messages, state after them) of a state with its count of changed rows in ``told``."""
    at, sent = [*keys, "id"], None
    for way, along in ways.items():
        active = now.filter("moved" if way is None else F.col("moved") & (F.col("direction") == way)).select(*keys, F.col("id").alias("src"), "value")
        met = along.join(small(active, now.told["moved"]), "src").select(*keys, F.col("dst").alias("id"), send(F.col("value"), F.col("w")).alias("value"))
        sent = met if sent is None else sent.unionByName(met)
    both = now.drop("moved").join(sent.groupBy(*at).agg(combine("value").alias("new")), at, "full_outer")
    moved = F.col("new").isNotNull() & (F.col("value").isNull() | better(F.col("new"), F.col("value")))
    return sent, both.select(*at, F.when(moved, F.col("new")).otherwise(F.col("value")).alias("value"), F.coalesce(moved, F.lit(False)).alias("moved"))
