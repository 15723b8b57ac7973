"""The given tables and the adapter views of the benchmark's data model, as DataFrames.

Each view is lazy; scans are pruned to the columns that a method uses.
"""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: Weight of each acuity, kinds of findings in order, relevance of each flag, tolerance of each age bucket.
SEVERITY = {"1-URGENT": 3, "2-HIGH": 3, "3-MEDIUM": 2, "4-NOT SPECIFIED": 2, "5-LOW": 1}
KINDS = {"STANDARD": "symptom", "ECONOMY": "sign", "MEDIUM": "lab", "PROMO": "imaging", "SMALL": "medication", "LARGE": "history"}
RELEVANCE = {"R": 3, "A": 2, "N": 1}
TOLERANCE = {"young": 7, "middle": 7, "older": 7}


def mapped(col: str, values: dict, default=None):
    out = None
    for k, v in values.items():
        out = F.when(F.col(col) == k, F.lit(v)) if out is None else out.when(F.col(col) == k, F.lit(v))
    return out.otherwise(F.lit(default))


class Tables:
    """Lazy access to tables (``t.orders``) and adapter views (``t.src_case``)."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        if name in NAMES:
            return self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")
        raise AttributeError(name)

    @property
    def case_lines(self) -> DataFrame:
        return self.lineitem

    def narrowed(self, cases: DataFrame) -> "Tables":
        """The same tables, with the views of cases over these cases only (the graph's views stay whole)."""
        return _Narrowed(self.spark, self.sf_dir, cases)

    def views(self) -> "Tables":
        """Registers the given tables as temporary views for SQL."""
        for n in NAMES:
            getattr(self, n).createOrReplaceTempView(n)
        return self

    @cached_property
    def src_case(self) -> DataFrame:
        return self.orders.join(self.customer, F.col("o_custkey") == F.col("c_custkey")).select(
            F.col("o_orderkey").alias("case_id"), F.col("o_custkey").alias("subject_id"), F.col("o_orderdate").alias("recorded_at"),
            (18 + (F.col("o_orderkey") * 7 + F.col("o_custkey") * 3) % 72).alias("age_years"), F.when(F.col("o_custkey") % 2 == 0, "F").otherwise("M").alias("sex"),
            F.col("c_mktsegment").alias("setting"), F.col("o_orderpriority").alias("acuity"),
        )

    @cached_property
    def dx_node(self) -> DataFrame:
        n = self.nation.join(F.broadcast(self.region), F.col("n_regionkey") == F.col("r_regionkey"))
        code = F.concat(F.substring("r_name", 1, 2), F.lpad(F.col("n_nationkey").cast("string"), 2, "0"), F.lit("."), F.lpad(F.col("s_suppkey").cast("string"), 6, "0"))
        return self.supplier.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("dx_id"), code.alias("code"), F.col("n_name").alias("category"), F.col("r_name").alias("chapter"))

    @cached_property
    def case_dx(self) -> DataFrame:
        pairs = self.case_lines.groupBy(F.col("l_orderkey").alias("case_id"), F.col("l_suppkey").alias("dx_id")).agg(F.max("l_extendedprice").alias("top"), F.max((F.col("l_linestatus") == "F").cast("int")).alias("final"))
        first = F.row_number().over(Window.partitionBy("case_id").orderBy(F.desc("top"), "dx_id"))
        return pairs.select("case_id", "dx_id", F.when(first == 1, "primary").when(F.col("final") == 1, "secondary").otherwise("differential").alias("role"))

    @cached_property
    def finding_node(self) -> DataFrame:
        return self.part.select(F.col("p_partkey").alias("finding_id"), F.col("p_name").alias("term"), mapped_prefix("p_type").alias("kind"), F.col("p_brand").alias("site"))

    @cached_property
    def case_finding(self) -> DataFrame:
        return self.case_lines.groupBy(F.col("l_orderkey").alias("case_id"), F.col("l_partkey").alias("finding_id")).agg(F.max(mapped("l_returnflag", RELEVANCE, 1)).alias("relevance"))

    @cached_property
    def dx_finding(self) -> DataFrame:
        out = self.lineitem.groupBy(F.col("l_suppkey").alias("dx_id"), F.col("l_partkey").alias("finding_id")).agg(F.count_distinct("l_orderkey").alias("n_cases"), F.max(mapped("l_returnflag", RELEVANCE, 1)).alias("grade"))
        return out.withColumn("etype", F.when(F.col("grade") == 3, "causes").when(F.col("grade") == 2, "suggests").otherwise("coexists"))

    @cached_property
    def chart_section(self) -> DataFrame:
        rows = self.case_finding.join(self.finding_node, "finding_id").withColumn("ord", kind_ord("kind"))
        return rows.groupBy("case_id", "kind", "ord").agg(F.array_join(F.array_sort(F.collect_set("term")), "; ").alias("body")).select((F.col("case_id") * 10 + F.col("ord")).alias("section_id"), "case_id", "ord", F.col("kind").alias("stype"), "body")

    @cached_property
    def raw_mention(self) -> DataFrame:
        rows = self.lineitem.select("l_orderkey", "l_partkey").distinct().join(self.part.select("p_partkey", "p_name"), F.col("l_partkey") == F.col("p_partkey"))
        k, w = (F.col("l_orderkey") + F.col("l_partkey")) % 5, F.split("p_name", " ")
        surface = F.when(k == 0, F.col("p_name")).when(k == 1, F.concat(F.lit("  "), F.upper("p_name"), F.lit(" "))).when(k == 2, F.concat_ws(" ", F.reverse(w)))
        surface = surface.when(k == 3, F.expr("substring(p_name, 1, length(p_name) - 1)")).otherwise(F.concat(F.lit("zz"), F.col("p_partkey").cast("string")))
        return rows.select(F.col("l_orderkey").alias("case_id"), F.col("l_partkey").alias("finding_id"), surface.alias("surface"), F.col("p_name").alias("true_term"))


class _Narrowed(Tables):
    def __init__(self, spark: SparkSession, sf_dir: str, cases: DataFrame):
        super().__init__(spark, sf_dir)
        self._ids = cases.select(F.col("case_id").alias("l_orderkey"))

    @property
    def case_lines(self) -> DataFrame:
        return self.lineitem.join(self._ids, "l_orderkey", "left_semi")


def mapped_prefix(col: str):
    return mapped_expr(F.substring_index(F.col(col), " ", 1))


def mapped_expr(head):
    out = None
    for k, v in KINDS.items():
        out = F.when(head == k, F.lit(v)) if out is None else out.when(head == k, F.lit(v))
    return out.otherwise(F.lit("other"))


def kind_ord(col: str):
    out = None
    for i, v in enumerate(KINDS.values(), 1):
        out = F.when(F.col(col) == v, F.lit(i)) if out is None else out.when(F.col(col) == v, F.lit(i))
    return out.otherwise(F.lit(7))


def severity(col: str = "acuity"):
    return mapped(col, SEVERITY, 1)


def age_bucket(col: str = "age_years"):
    return F.when(F.col(col) < 40, "young").when(F.col(col) < 65, "middle").otherwise("older")
