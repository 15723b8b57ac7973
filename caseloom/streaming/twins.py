"""Registered streams: a whole table read as a stream until nothing is left, its result written below the shared checkpoint folder."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ..plans.checkpoint import ready


def drained(stream: DataFrame, schema: str) -> DataFrame:
    """The complete result of an aggregated stream after all files.

    Each micro-batch replaces the result table, so a repeated batch after a lost driver changes nothing.
    """
    spark = stream.sparkSession
    path = f"{ready(spark)}/stream-{uuid.uuid4().hex}"
    put: Callable[[DataFrame, int], None] = lambda batch, _: batch.write.mode("overwrite").parquet(f"{path}/out")
    stream.writeStream.outputMode("complete").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.schema(schema).parquet(f"{path}/out")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calls per tool and day, by the streaming query over the whole table."""
    from pyspark.sql import functions as F

    from .calls import read_calls
    from .calls import tumbling as windows

    # A stream's source is a folder or a pattern; the pattern names the one table.
    days = windows(read_calls(spark, f"{sf_dir}/events.parque[t]")).select("event_type", F.col("start").cast("date").cast("string").alias("day"), "n")
    return drained(days, "event_type string, day string, n long")
