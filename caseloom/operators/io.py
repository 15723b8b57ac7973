"""Registered queries: sources, sinks, round trips and table functions."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions import stats as X
from ..plans.oracle import sql
from ..sources.bundles import BundleSource
from ..sources.tables import Tables
from ..streaming import twins
from .registry import register


def folder(spark) -> str:
    """A new folder below the shared checkpoint folder."""
    from ..plans.checkpoint import ready

    return f"{ready(spark)}/io-{uuid.uuid4().hex}"


def round_trip(fmt: str):
    def run(spark, sf_dir):
        src = Tables(spark, sf_dir).orders.select("o_orderkey", "o_custkey", "o_orderpriority")
        path = folder(spark)
        src.write.format(fmt).save(path)
        return spark.read.schema(src.schema).format(fmt).load(path)

    return run


def partitioned(spark, sf_dir):
    """A label store by split; a read of one split opens its folder only."""
    path = folder(spark)
    Tables(spark, sf_dir).customer.select("c_custkey", F.when(F.col("c_custkey") % 5 == 0, "public").otherwise("training").alias("split")).write.partitionBy("split").parquet(path)
    return spark.read.parquet(path).where("split = 'public'").select("c_custkey")


@udtf(returnType="ord int, stype string, n int")
class Sections:
    """Lines of a text as sections, in order."""

    def eval(self, text: str):
        for i, line in enumerate((text or "").split("\n")):
            if line:
                yield i, "table" if "|" in line else "notice" if "licen" in line.lower() else "narrative", len(line)


def sections(spark, sf_dir):
    Tables(spark, sf_dir).documents.select("doc_id", "text").createOrReplaceTempView("_texts")
    spark.udtf.register("sections_of", Sections)
    return spark.sql("SELECT doc_id, s.ord, s.stype, s.n FROM _texts, LATERAL sections_of(text) AS s")


def bundles(spark, sf_dir):
    """Patients' encounters written as NDJSON resources and read back by the Python data source, a task for each file."""
    t, path = Tables(spark, sf_dir), folder(spark)
    body = F.struct(F.col("case_id").alias("encounter"), F.col("acuity"))
    t.src_case.select(F.lit("Encounter").alias("kind"), F.col("case_id").cast("string").alias("id"), body.alias("body")).write.json(path)
    spark.dataSource.register(BundleSource)
    return spark.read.format("bundle").option("files", ",".join(spark.read.text(path).inputFiles())).load()


def binomials(spark, sf_dir):
    """For each patient, whether urgent encounters are as frequent as others; equal counts are computed once."""
    urgent = F.count_if(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH"))
    of = Tables(spark, sf_dir).orders.groupBy("o_custkey").agg(F.count("*").alias("n"), urgent.alias("k"))
    p = of.select("k", "n").distinct().withColumn("p", F.round(X.binom_p("k", "n"), 9))
    return of.join(p, ["k", "n"]).select("o_custkey", "k", "n", "p")


for f in ("json", "csv", "orc"):
    register(f"q_io_roundtrip_{f}", round_trip(f), "SELECT o_orderkey, o_custkey, o_orderpriority FROM orders")
register("q_sink_partitioned", partitioned, "SELECT c_custkey FROM customer WHERE c_custkey % 5 = 0")
register("q_udtf_sections", sections, "SELECT doc_id, CAST(i - 1 AS INT) AS ord, CASE WHEN contains(line, '|') THEN 'table' WHEN contains(lower(line), 'licen') THEN 'notice' ELSE 'narrative' END AS stype, CAST(length(line) AS INT) AS n FROM (SELECT doc_id, i, parts[i] AS line FROM (SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS i FROM (SELECT doc_id, string_split(text, chr(10)) AS parts FROM documents))) WHERE length(line) > 0")
LOG = "lgamma(n + 1) - lgamma({0} + 1) - lgamma(n - {0} + 1) + n * ln(0.5)"
URGENT = "(SELECT o_custkey, count(*) AS n, count(*) FILTER (WHERE o_orderpriority IN ('1-URGENT', '2-HIGH')) AS k FROM orders GROUP BY 1)"
P = f"(SELECT k, n, round(least(1.0, sum(exp({LOG.format('i')})) FILTER (WHERE {LOG.format('i')} <= {LOG.format('k')} + 1e-9)), 9) AS p FROM (SELECT k, n, unnest(range(0, n + 1)) AS i FROM (SELECT DISTINCT k, n FROM {URGENT})) GROUP BY 1, 2)"
register("q_udf_binom", binomials, f"SELECT o_custkey, k, n, p FROM {URGENT} JOIN {P} USING (k, n)")
register(
    "q_ds_bundle",
    bundles,
    sql("SELECT 'Encounter' AS kind, CAST(case_id AS VARCHAR) AS id, CAST(to_json({'encounter': case_id, 'acuity': acuity}) AS VARCHAR) AS body FROM src_case"),
)
register("q_stream_twin_tumbling", twins.tumbling, "SELECT event_type, CAST(CAST(date_trunc('day', ts) AS DATE) AS VARCHAR) AS day, count(*) AS n FROM events GROUP BY 1, 2")
