"""Lineage cuts in the shared checkpoint folder of the session."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def ready(spark: SparkSession) -> str:
    """The checkpoint folder of the session; where it names none, as in local tests, a folder is made."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="caseloom-"))
    return sc._jsc.sc().getCheckpointDir().get()


def durable(df: DataFrame) -> DataFrame:
    """Cuts the lineage with a checkpoint in ``spark.checkpoint.dir``."""
    ready(df.sparkSession)
    return df.checkpoint(eager=True)


class Packed:
    """A frame written as Parquet in the checkpoint folder, several times smaller than a checkpoint, until ``drop``; a folder for each value of ``by``."""

    def __init__(self, df: DataFrame, *by: str):
        self.spark, self.path = df.sparkSession, f"{ready(df.sparkSession)}/packed-{uuid.uuid4().hex}"
        df.write.partitionBy(*by).parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)


def drop(*frames: Packed) -> None:
    """Deletes the frames' own folders, and clears shuffles."""
    for x in frames:
        path = x.spark._jvm.org.apache.hadoop.fs.Path(x.path)
        path.getFileSystem(x.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
        del x.df
    clear(frames[0].spark)


def clear(spark: SparkSession) -> None:
    """Lets Spark clear the shuffles that nothing refers to any more."""
    gc.collect()
    spark._jvm.System.gc()
