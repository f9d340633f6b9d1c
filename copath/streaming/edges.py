"""Edges and supports from event streams."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def _next_events(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    # An event waits until the watermark has passed it: only then can no earlier one still come.
    last, times, ids = state.get if state.exists else (None, [], [])
    rows = [(t, i) for t, i in zip(times, ids)]
    if not state.hasTimedOut:
        for b in batches:
            rows += [(int(t.value) // 1000, int(i)) for t, i in zip(b["ts"], b["event_id"])]
    limit = state.getCurrentWatermarkMs() * 1000
    rows.sort()
    ready = [i for t, i in rows if t <= limit]
    chain = ([last] if last is not None else []) + ready
    rows = rows[len(ready) :]
    if chain and not rows and not ready and state.hasTimedOut:
        state.remove()
    else:
        state.update((chain[-1] if chain else None, [t for t, _ in rows], [i for _, i in rows]))
        # The next event that waits, or a day without any: then the user is forgotten.
        due = rows[0][0] // 1000 if rows else limit // 1000 + 86_400_000
        state.setTimeoutTimestamp(max(limit // 1000 + 1, due + 1))
    if len(chain) > 1:
        yield pd.DataFrame({"src": chain[:-1], "dst": chain[1:]})


def next_edges(events: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """src, label ``next``, dst: each event and the next one of its user by (ts, event_id), once the watermark has passed both.

    The state of a user is the last such event and those that still wait; a day of event time without events ends it. Events
    that come later than the watermark are dropped.
    """
    own = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id").withWatermark("ts", watermark)
    late_free = own.groupBy("user_id").applyInPandasWithState(_next_events, "src long, dst long", "last long, times array<long>, ids array<long>", "append", GroupStateTimeout.EventTimeTimeout)
    return late_free.select("src", F.lit("next").alias("label"), "dst")


def unit_support(events: DataFrame, window: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """window_start, pattern, support: distinct users of each {type} event in tumbling or sliding windows; late rows are dropped."""
    own = events.select(F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type").withWatermark("ts", watermark)
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    once = own.select(w.alias("w"), "user_id", "event_type").dropDuplicates(["w", "user_id", "event_type"])
    return once.groupBy("w", "event_type").agg(F.count("*").alias("support")).select(F.col("w.start").alias("window_start"), F.concat(F.lit("{type:"), "event_type", F.lit("}")).alias("pattern"), "support")


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str | None = "1 hour") -> DataFrame:
    """user_id, session_start, session_end, n_events: runs of a user's events less than ``gap`` apart."""
    own = events.select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    if watermark:
        own = own.withWatermark("ts", watermark)
    return own.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n_events")).select("user_id", F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "n_events")


def remine(edges: DataFrame, path: str, mine):
    """A query that adds each batch of edges to the table at ``path`` and calls ``mine(table, batch number)``. A batch that comes again replaces itself."""

    def step(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(path)
        mine(batch.sparkSession.read.parquet(path).drop("batch").distinct(), number)

    return edges.writeStream.foreachBatch(step)
