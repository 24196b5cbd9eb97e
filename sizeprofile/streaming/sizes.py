"""Windowed group sizes on event time, and a release for each closed window."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.budget import BudgetLedger


def events_stream(spark, folder: str, schema: str = "event_id long, ts timestamp_ntz, user_id long, event_type string, props string") -> DataFrame:
    return spark.readStream.schema(schema).parquet(folder)


def timed(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Event time as a timestamp with a watermark: rows later than `lateness` are dropped."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def tumbling_sizes(events: DataFrame, length: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """(window, user_id, size). Each event is in one window, so windows compose in parallel."""
    return timed(events, lateness).groupBy(F.window("ts", length), "user_id").agg(F.count(F.lit(1)).alias("size"))


def sliding_sizes(events: DataFrame, length: str = "1 day", step: str = "6 hours", lateness: str = "1 hour") -> DataFrame:
    """(window, user_id, size). An event is in length / step windows, so the budget of each is that much smaller."""
    return timed(events, lateness).groupBy(F.window("ts", length, step), "user_id").agg(F.count(F.lit(1)).alias("size"))


def session_sizes(events: DataFrame, gap: str = "30 minutes", lateness: str = "1 hour") -> DataFrame:
    """(session, user_id, size). Session bounds depend on the data, so groups are not public: sizes only, no release."""
    return timed(events, lateness).groupBy(F.session_window("ts", gap).alias("session"), "user_id").agg(F.count(F.lit(1)).alias("size"))


def deduplicated(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Each event id once within the watermark."""
    return timed(events, lateness).dropDuplicatesWithinWatermark(["event_id"])


def with_public_users(sizes: DataFrame, users: DataFrame) -> DataFrame:
    """All public users in each window, so that whether a user was active is not revealed by the set of groups."""
    windows = sizes.select("window").distinct()  # as many as the batch closes; users grow with the data and stay where they are
    return users.select("user_id").join(F.broadcast(windows)).join(sizes, ["window", "user_id"], "left").select("window", "user_id", F.coalesce("size", F.lit(0)).cast("long").alias("size"))


def release_each_batch(ledger: BudgetLedger, eps: float, make: Callable[[DataFrame, float], DataFrame], path: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: one draw a closed window, written under its batch id, which a replay finds and skips."""

    def write(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        out = f"{path}/batch={batch_id}"
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{out}/_SUCCESS")
        if target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(target):
            return
        ledger.spend("stream", eps, f"batch {batch_id}")
        make(batch, eps).write.mode("overwrite").parquet(out)

    return write


def closed_sizes(events: DataFrame, idle: str = "30 minutes", lateness: str = "1 hour") -> DataFrame:
    """(user_id, begin, end, size) of each activity period, emitted once it is over: a period ends after `idle` without an event.

    A stateful processor on streams: a user's state is the few open periods (begin, end, size) in the order of time, which late
    events may extend or join. An event-time timer closes a period when the watermark has passed its end by `idle`.
    Like sessions, periods depend on the data and are not to be released.
    """
    from pyspark.sql.streaming.state import GroupStateTimeout

    gap = pd.Timedelta(idle)

    def step(key, batches, state):
        open_ = [list(x) for x in zip(*state.get)] if state.exists else []
        for pdf in batches:
            open_ += [[t, t, 1] for t in pdf["ts"].astype("int64") // (1000 if str(pdf["ts"].dtype).startswith("datetime64[ns") else 1)]
        merged: list[list[int]] = []
        for begin, end, n in sorted(open_):
            if merged and begin - merged[-1][1] < gap.value // 1000:
                merged[-1][1], merged[-1][2] = max(end, merged[-1][1]), merged[-1][2] + n
            else:
                merged.append([begin, end, n])
        mark = state.getCurrentWatermarkMs() * 1000
        over = [p for p in merged if p[1] + gap.value // 1000 <= mark]
        left = [p for p in merged if p[1] + gap.value // 1000 > mark]
        if left:
            state.update(tuple([p[k] for p in left] for k in range(3)))
            state.setTimeoutTimestamp(max(mark // 1000 + 1, (left[0][1] + gap.value // 1000) // 1000))
        elif state.exists:
            state.remove()
        if over:
            yield pd.DataFrame({"user_id": [key[0]] * len(over), "begin": pd.to_datetime([p[0] for p in over], unit="us", utc=True), "end": pd.to_datetime([p[1] for p in over], unit="us", utc=True), "size": [p[2] for p in over]})

    rows = timed(events, lateness).select("user_id", "ts")
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, begin timestamp, end timestamp, size long", "begins array<long>, ends array<long>, sizes array<long>", "append", GroupStateTimeout.EventTimeTimeout)
