"""Edges that arrive as a stream of events: state a user, state a destination, windows, late and repeated rows."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def session_edges(events: DataFrame) -> DataFrame:
    """(src, dst, user_id): each event's edge to the user's next one, made when the next one arrives.

    The state of a user is their last event.  Within a batch events go by (ts, event_id); an event older than the last
    one comes too late for its place in the chain and makes no edge.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["us", "event_id"])
        last = state.get if state.exists else None
        out = []
        for us, event in zip(rows["us"], rows["event_id"]):
            if last is not None and (us, event) <= tuple(last):
                continue
            if last is not None:
                out.append((last[1], event, key[0]))
            last = (int(us), int(event))
        if last is not None:
            state.update(last)
        yield pd.DataFrame(out, columns=["src", "dst", "user_id"])

    rows = events.where("user_id is not null and event_id is not null and ts is not null").select("user_id", "event_id", F.unix_micros("ts").alias("us"))
    return rows.groupBy("user_id").applyInPandasWithState(step, "src long, dst long, user_id long", "us long, event_id long", "append", GroupStateTimeout.NoTimeout)


def completed_sums(messages: DataFrame, timeout: str | None = None) -> DataFrame:
    """(dst, total, missing): a destination's sum of messages (dst, d_in, value) when its last one is in.

    The state is the pending count and the partial sum, that is a slot of the resident store.  With a timeout (such as
    "1 hour") a destination that stays open so long is put out with what it has and the number that is missing.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            pending, total = state.get
            state.remove()
            yield pd.DataFrame({"dst": [key[0]], "total": [total], "missing": [pending]})
            return
        pending, total = state.get if state.exists else (None, 0)
        for f in frames:
            if not len(f):
                continue
            pending = int(f["d_in"].iloc[0]) if pending is None else pending
            pending -= len(f)
            total += int(f["value"].sum())
        if pending == 0:
            if state.exists:
                state.remove()
            yield pd.DataFrame({"dst": [key[0]], "total": [total], "missing": [0]})
            return
        state.update((pending, total))
        if timeout:
            state.setTimeoutDuration(timeout)

    kind = GroupStateTimeout.ProcessingTimeTimeout if timeout else GroupStateTimeout.NoTimeout
    return messages.groupBy("dst").applyInPandasWithState(step, "dst long, total long, missing int", "pending int, total long", "append", kind)


def windowed_counts(events: DataFrame, window: str = "1 hour", late: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by window and type; those later than the watermark are left out."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events.withWatermark("ts", late).groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def first_arrivals(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events once each, if the repetition comes within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def joined_pairs(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """(a, b): events of the two streams by one user, the right one at most ``within`` later."""
    l = left.withWatermark("ts", within).select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("at"))  # noqa: E741
    r = right.withWatermark("ts", within).select(F.col("event_id").alias("b"), F.col("user_id").alias("u"), F.col("ts").alias("then"))
    return l.join(r, F.expr(f"user_id = u AND then >= at AND then <= at + INTERVAL {within}")).select("a", "b")


def drain(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now and returns its rows."""
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return df.sparkSession.table(name)
