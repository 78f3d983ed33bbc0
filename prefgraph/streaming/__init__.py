"""Ballots that arrive as a stream: margins are sums over voters, so each micro-batch adds its own."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.ballots import from_scores
from ..operators.margins import head_to_head


def window_counts(events: DataFrame, window: str = "1 day", watermark: str = "1 hour") -> DataFrame:
    """(voter, alt, score): event types counted by user and tumbling window; rows later than the watermark are dropped."""
    counted = events.withWatermark("ts", watermark).groupBy(F.window("ts", window).alias("win"), "user_id", "event_type").agg(F.count(F.lit(1)).alias("score"))
    return counted.select(F.concat_ws("@", F.col("user_id").cast("string"), F.unix_timestamp(F.col("win.start")).cast("string")).alias("voter"), F.col("event_type").alias("alt"), "score")


def margin_updates(events: DataFrame, sink: str, checkpoint: str, window: str = "1 day", watermark: str = "1 hour"):
    """Start a query that appends the margins of every micro-batch of closed windows to sink, in a folder of the batch's number, so that a
    repeated batch overwrites its own rows."""

    def add(batch: DataFrame, number: int) -> None:
        head_to_head(from_scores(batch, "voter", "alt", "score")).write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return window_counts(events, window, watermark).writeStream.outputMode("append").foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def current_margins(spark: SparkSession, sink: str) -> DataFrame:
    return spark.read.schema("a string, b string, margin long, batch int").parquet(sink).groupBy("a", "b").agg(F.sum("margin").cast("long").alias("margin"))


def latest_ballots(events: DataFrame, timeout_ms: int = 3_600_000) -> DataFrame:
    """(user_id, event_type, ts) whenever a user's newest event changes: state keeps one ballot a user and replaces it."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def replace(key: tuple, batches, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        kept = state.get if state.exists else ("", -1)
        for batch in batches:
            row = batch.sort_values(["ts", "event_type"]).iloc[-1]
            stamp = int(row.ts.value // 1000)
            if stamp >= kept[1]:
                kept = (row.event_type, stamp)
        state.update(kept)
        state.setTimeoutDuration(timeout_ms)
        yield pd.DataFrame({"user_id": [key[0]], "event_type": [kept[0]], "ts_micros": [kept[1]]})

    return events.groupBy("user_id").applyInPandasWithState(replace, "user_id long, event_type string, ts_micros long", "event_type string, ts long", "update", GroupStateTimeout.ProcessingTimeTimeout)
