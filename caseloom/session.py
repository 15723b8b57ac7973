"""A session with the settings that tests and the bench use."""

from __future__ import annotations

from pyspark.sql import SparkSession


def get_spark(app: str = "caseloom", cores: int | str = "*", **conf: str) -> SparkSession:
    base = {"spark.sql.shuffle.partitions": "8", "spark.sql.session.timeZone": "UTC", "spark.sql.adaptive.enabled": "true", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false"}
    return SparkSession.builder.appName(app).master(f"local[{cores}]").config(map=base | conf).getOrCreate()
