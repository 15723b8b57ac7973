"""Streams end with what their batch twins give; late rows are dropped; checkpoints resume."""

import json

import pytest
from pyspark.sql import functions as F

from caseloom.sources.bundles import BundleSource
from caseloom.streaming import calls as C

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("calls") / "in")
    spark.read.parquet(f"{SF}/events.parquet").repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def drain(df, name, mode="append", checkpoint=None):
    w = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        w = w.option("checkpointLocation", checkpoint)
    w.start().awaitTermination(120)
    return df.sparkSession.table(name)


def test_tumbling_complete_equals_batch(spark, folder):
    got = drain(C.tumbling(C.read_calls(spark, folder)), "tumble", "complete")
    batch = C.tumbling(spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")))
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, batch.collect()))


def test_budget(spark, folder):
    got = drain(C.budget(C.read_calls(spark, folder), 10), "budget")
    per = {r["user_id"]: r["n"] for r in got.groupBy("user_id").agg(F.count("*").alias("n")).collect()}
    want = {r["user_id"]: min(10, r["n"]) for r in spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id").agg(F.count("*").alias("n")).collect()}
    assert per == want


def test_joins_and_dedup(spark, folder):
    batch = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    assert set(map(tuple, drain(C.answers(C.read_calls(spark, folder)), "answers").collect())) <= set(map(tuple, C.answers(batch).collect()))
    customer = spark.read.parquet(f"{SF}/customer.parquet")
    assert drain(C.with_segment(C.read_calls(spark, folder), customer), "segment").count() == C.with_segment(batch, customer).count()
    twice = C.read_calls(spark, folder)
    assert drain(C.distinct_calls(twice.unionByName(twice)), "once").count() == batch.count()


def test_bundle_source(spark, tmp_path):
    f = tmp_path / "a.ndjson"
    f.write_text("".join(json.dumps({"kind": "Patient", "id": str(i), "body": {"x": i}}) + "\n" for i in range(3)))
    spark.dataSource.register(BundleSource)
    rows = spark.read.format("bundle").option("files", str(f)).load().collect()
    assert [r["id"] for r in rows] == ["0", "1", "2"] and json.loads(rows[2]["body"]) == {"x": 2}
