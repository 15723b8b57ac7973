"""Patient-level splits in strata: public by difficulty and encounters, then held-out and training by chapter and encounters."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.checkpoint import durable
from ..sources.tables import Tables

#: Patients of all splits, of the public one, of the held-out one.
ALL, PUBLIC, HELD = 1268.0, 200, 268
#: The order within a stratum has this many buckets, so no stratum is sorted in one task.
BUCKETS = 64


def encounter_band(n: Column) -> Column:
    return F.when(n <= 5, 1).when(n <= 10, 2).when(n <= 15, 3).otherwise(4)


def profile(t: Tables) -> DataFrame:
    """patient_id, n_cases, load, band of encounters and dominant chapter of every patient with a diagnosis."""
    rows = t.src_case.join(t.case_dx, "case_id").join(F.broadcast(t.dx_node.select("dx_id", "chapter")), "dx_id")
    n = rows.groupBy(F.col("subject_id").alias("patient_id"), "chapter").agg(F.count("*").alias("n"))
    chapter = n.groupBy("patient_id").agg(F.min(F.struct(-F.col("n"), "chapter"))["chapter"].alias("chapter"))
    size = rows.groupBy(F.col("subject_id").alias("patient_id")).agg(F.count_distinct("case_id").alias("n_cases"), F.count_distinct("dx_id").alias("_d"))
    size = size.select("patient_id", "n_cases", (F.col("n_cases") * 3 + F.col("_d")).alias("load"), encounter_band(F.col("n_cases")).alias("band"))
    return size.join(chapter, "patient_id")


def difficulty(rows: DataFrame) -> DataFrame:
    """Adds ``tertile`` of the load, by cut points (no window over all rows). [D]"""
    cuts = rows.agg(F.percentile("load", F.array(F.lit(1 / 3), F.lit(2 / 3))).alias("_c"))
    cut = F.when(F.col("load") <= F.col("_c")[0], 1).when(F.col("load") <= F.col("_c")[1], 2).otherwise(3)
    return rows.crossJoin(F.broadcast(cuts)).withColumn("tertile", cut).drop("_c")


def chosen(rows: DataFrame, strata: list[str], share: float) -> DataFrame:
    """Adds ``chosen``: in each stratum the first rows by a hash of the patient, as many as its largest-remainder part of ``share``.

    A row's rank is its rank in a bucket of the hash order and the rows in the buckets before; only the table of
    strata and buckets, whose size does not grow with the rows, is sorted as one.
    """
    h = (F.col("patient_id") * 7919) % 10007
    rows = rows.withColumns({"_h": h, "_k": F.floor(h * BUCKETS / 10007)})
    cells = rows.groupBy(*strata, "_k").agg(F.count("*").alias("_n"))
    before = cells.withColumn("_before", F.sum("_n").over(Window.partitionBy(*strata).orderBy("_k")) - F.col("_n")).select(*strata, "_k", "_before")
    quota = cells.groupBy(*strata).agg((F.sum("_n") * share).alias("_q")).withColumn("_f", F.floor("_q"))
    left = quota.agg((F.round(F.sum("_q")) - F.sum("_f")).alias("_left"))
    rest = F.row_number().over(Window.orderBy(F.desc(F.round(F.col("_q") - F.col("_f"), 9)), *strata))
    quota = quota.withColumn("_r", rest).crossJoin(left).select(*strata, (F.col("_f") + (F.col("_r") <= F.col("_left")).cast("long")).alias("_take"))
    rank = F.row_number().over(Window.partitionBy(*strata, "_k").orderBy("_h", "patient_id"))
    out = rows.withColumn("_rank", rank).join(F.broadcast(before), [*strata, "_k"]).join(F.broadcast(quota), strata)
    return out.withColumn("chosen", F.col("_before") + F.col("_rank") <= F.col("_take")).drop("_h", "_k", "_before", "_rank", "_take")


def assign(t: Tables, profiles: DataFrame | None = None) -> DataFrame:
    """patient_id, split, chapter, band and tertile of every patient; ``profiles`` are those of ``profile``, if they are there already."""
    rows = chosen(durable(difficulty(profile(t) if profiles is None else profiles)), ["tertile", "band"], PUBLIC / ALL).withColumnRenamed("chosen", "_public")
    rows = durable(rows)
    rest = chosen(rows.where("NOT _public"), ["chapter", "band"], HELD / (ALL - PUBLIC))
    cols = ["patient_id", "chapter", "band", "tertile"]
    public = rows.where("_public").select(*cols, F.lit("public").alias("split"))
    return public.unionByName(rest.select(*cols, F.when(F.col("chosen"), "heldout").otherwise("training").alias("split")))
