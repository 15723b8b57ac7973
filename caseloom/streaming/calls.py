"""Structured Streaming over the tool-call log: windows, budgets, joins and late rows.

Every function takes and returns a frame, streaming or not; batch twins of the results are
registered as queries.  Event time is ``ts`` (a timestamp; the given table's has no zone and is
cast before any watermark).
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def read_calls(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    """A stream of Parquet files of calls."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(calls: DataFrame, late: str = "1 hour", size: str = "1 day") -> DataFrame:
    """Calls per tool and window; rows later than the watermark are dropped."""
    return calls.withWatermark("ts", late).groupBy("event_type", F.window("ts", size).alias("w")).agg(F.count("*").alias("n")).select("event_type", F.col("w.start").alias("start"), "n")


def sliding(calls: DataFrame, late: str = "1 hour", size: str = "24 hours", step: str = "6 hours") -> DataFrame:
    return calls.withWatermark("ts", late).groupBy(F.window("ts", size, step).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(calls: DataFrame, late: str = "1 hour", gap: str = "12 hours") -> DataFrame:
    return calls.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def budget(calls: DataFrame, most: int = 40, idle: str = "7 days") -> DataFrame:
    """The first ``most`` calls of each user; the state is one counter and goes after an idle time."""

    def keep(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        used = state.get[0] if state.exists else 0
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = rows.head(max(0, most - used))[["user_id", "event_id"]]
        state.update((used + len(rows),))
        state.setTimeoutTimestamp(max(int(rows["ts"].max().timestamp() * 1000), state.getCurrentWatermarkMs()) + int(pd.Timedelta(idle).total_seconds() * 1000))
        yield out

    return calls.withWatermark("ts", "1 hour").groupBy("user_id").applyInPandasWithState(keep, "user_id long, event_id long", "used long", "append", GroupStateTimeout.EventTimeTimeout)


def answers(calls: DataFrame, answer: str = "purchase", within: str = "1 hour") -> DataFrame:
    """Calls with an answer of the same user within a time; both sides are watermarked, so state is bounded."""
    left = calls.withWatermark("ts", "1 hour").where(F.col("event_type") != answer).select("user_id", F.col("ts").alias("called"), F.col("event_id").alias("call"))
    right = calls.withWatermark("ts", "1 hour").where(F.col("event_type") == answer).select(F.col("user_id").alias("_u"), F.col("ts").alias("answered"), F.col("event_id").alias("answer"))
    return left.join(right, F.expr(f"user_id = _u AND answered > called AND answered <= called + INTERVAL {within}")).select("call", "answer")


def with_segment(calls: DataFrame, customer: DataFrame) -> DataFrame:
    """Calls with their user's segment, a static table."""
    return calls.join(customer.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")


def distinct_calls(calls: DataFrame, late: str = "1 hour") -> DataFrame:
    """Replayed calls once, by event_id within the watermark."""
    return calls.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
