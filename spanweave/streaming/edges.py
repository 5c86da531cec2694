"""Edges from event streams, and estimates kept up to date by them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

CHAIN_SCHEMA = "user_id bigint, src bigint, dst bigint, w bigint"


def transition_windows(events: DataFrame, *, width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(window start, event_type, n, least value): edges' raw material by time window; batch or stream."""
    by = F.window("ts", width, slide) if slide else F.window("ts", width)
    source = events.withWatermark("ts", late) if events.isStreaming else events
    rows = source.groupBy(by.alias("win"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("least"))
    return rows.select(F.col("win.start").alias("started"), "event_type", "n", "least")


def session_windows(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(started, ended, user_id, n): sessions of a user that end after a gap; batch or stream."""
    source = events.withWatermark("ts", late) if events.isStreaming else events
    rows = source.groupBy(F.session_window("ts", gap).alias("win"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return rows.select(F.col("win.start").alias("started"), F.col("win.end").alias("ended"), "user_id", "n")


def chain_edges(events: DataFrame, *, late: str = "10 minutes") -> DataFrame:
    """Edges between a user's consecutive events as they arrive: the last event of each user is kept as state and dropped by event-time timeout."""

    def follow(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        ids, at = rows["event_id"].tolist(), [int(t.timestamp()) for t in rows["ts"]]
        if state.exists:
            before, when = state.get
            ids, at = [before, *ids], [when, *at]
        state.update((ids[-1], at[-1]))
        state.setTimeoutTimestamp(max(at[-1] * 1000 + 30 * 86_400_000, state.getCurrentWatermarkMs() + 1))
        if len(ids) > 1:
            ends, w = list(zip(ids, ids[1:])), [max(1, b - a) for a, b in zip(at, at[1:])]
            yield pd.DataFrame({"user_id": key[0], "src": [min(p) for p in ends], "dst": [max(p) for p in ends], "w": w})

    source = events.select("user_id", "event_id", "ts").withWatermark("ts", late)
    return source.groupBy("user_id").applyInPandasWithState(follow, CHAIN_SCHEMA, "event bigint, at bigint", "append", GroupStateTimeout.EventTimeTimeout)


def distinct_events(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_user(events: DataFrame, users: DataFrame) -> DataFrame:
    """Stream-static join on user_id."""
    return events.join(users, "user_id")


def proximity(a: DataFrame, b: DataFrame, seconds: int, late: str = "10 minutes") -> DataFrame:
    """Stream-stream interval join: events of one user in both streams at most ``seconds`` apart."""
    x = a.select(F.col("user_id").alias("user_a"), F.col("event_id").alias("event_a"), F.col("ts").alias("ts_a")).withWatermark("ts_a", late)
    y = b.select(F.col("user_id").alias("user_b"), F.col("event_id").alias("event_b"), F.col("ts").alias("ts_b")).withWatermark("ts_b", late)
    near = F.expr(f"user_a = user_b AND ts_b BETWEEN ts_a - INTERVAL {seconds} SECONDS AND ts_a + INTERVAL {seconds} SECONDS")
    return x.join(y, near).filter("event_a <> event_b")


def keep_estimate(edges: DataFrame, estimate: Callable[[DataFrame], dict], known: dict) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function that merges new edges into ``known['edges']`` and estimates anew only where the old bound may fail.

    Added or lightened edges within a component never lengthen a distance there, so the old upper bound stays valid. A new
    node, or an edge between two known components, can make the largest distance grow and forces a rerun. A batch that is
    repeated after a failure changes nothing."""
    known.setdefault("edges", edges)

    def merge(batch: DataFrame, epoch: int) -> None:
        from spanweave.operators.components import connected_components
        from spanweave.session import stored

        new = batch.select("src", "dst", "w").filter("src <> dst")
        if "parts" not in known:
            known["parts"] = connected_components(known["edges"], "src", "dst")
        at = lambda end: known["parts"].select(F.col("node").alias(f"_{end}"), F.col("component").alias(f"{end}_part"))
        placed = new
        for end in ("src", "dst"):
            placed = placed.join(at(end), F.col(end) == F.col(f"_{end}"), "left")
        apart = ~F.coalesce(F.col("src_part") == F.col("dst_part"), F.lit(False))
        grows = not placed.filter(apart).isEmpty()
        both = known["edges"].select("src", "dst", "w").unionByName(new)
        known["edges"] = stored(both.groupBy("src", "dst").agg(F.min("w").alias("w")), "known")
        if grows:
            known["parts"] = connected_components(known["edges"], "src", "dst")
        if grows or "result" not in known:
            known["result"] = estimate(known["edges"])
            known["runs"] = known.get("runs", 0) + 1

    return merge
