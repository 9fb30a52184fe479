"""Spacing in streams: per key, an event stays if it is at least h after the last one that stayed."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

SCHEMA = "user_id long, event_id long, ts timestamp"


def walk(frame: pd.DataFrame, last, h: pd.Timedelta) -> tuple[list[int], object]:
    keep = []
    for k, ts in enumerate(frame["ts"]):
        if last is None or ts - last >= h:
            keep.append(k)
            last = ts
    return keep, last


def spaced_batch(events: DataFrame, seconds: int) -> DataFrame:
    """The same rule over a table: a task for each user."""

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["ts", "event_id"]).reset_index(drop=True)
        keep, _ = walk(frame, None, pd.Timedelta(seconds=seconds))
        return frame.loc[keep, ["user_id", "event_id", "ts"]]

    return events.filter("user_id IS NOT NULL AND ts IS NOT NULL").select("user_id", "event_id", "ts").groupBy("user_id").applyInPandas(one, SCHEMA)


def spaced_stream(events: DataFrame, seconds: int, late: str = "1 day") -> DataFrame:
    """The same over a stream whose events arrive in order of time for each user; state: one time a user, dropped when the watermark passes it by h."""
    h = pd.Timedelta(seconds=seconds)

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        last = pd.Timestamp(state.get[0], unit="us") if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"]).reset_index(drop=True)
        keep, last = walk(rows, last, h)
        state.update((int(last.value // 1000),))
        state.setTimeoutTimestamp(int(last.value // 10**6) + seconds * 1000)
        yield rows.loc[keep, ["user_id", "event_id", "ts"]]

    source = events.withWatermark("ts", late).select("user_id", "event_id", "ts")
    return source.groupBy("user_id").applyInPandasWithState(step, SCHEMA, "last long", "append", GroupStateTimeout.EventTimeTimeout)


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what there is and returns the result table."""
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def tumbling(events: DataFrame, size: str) -> DataFrame:
    return events.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, size: str, step: str) -> DataFrame:
    return events.groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def late_rows(events: DataFrame, seconds: int) -> DataFrame:
    """Rows more than so many seconds behind the latest time seen before them, in order of arrival (event_id) for each user."""
    seen = F.max("ts").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    return events.withColumn("seen", seen).filter(F.unix_micros("seen") - F.unix_micros("ts") > seconds * 1_000_000).select("user_id", "event_id")


def deduplicated(events: DataFrame, window: str) -> DataFrame:
    return events.withWatermark("ts", window).dropDuplicatesWithinWatermark(["user_id", "event_type"])
