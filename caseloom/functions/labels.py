"""Labels as functions of the graph, and the panel that stands in for systems that cannot run here."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.checkpoint import durable
from ..sources.tables import Tables, kind_ord, severity
from . import links, splits

#: Fixed values of the simulated panel: system, per cent of gold dropped, per cent of noise.
PANEL = [(1, 32, 12), (2, 30, 11), (3, 27, 10), (4, 38, 14), (5, 34, 18), (6, 34, 15), (7, 35, 16), (8, 32, 20), (9, 46, 24), (10, 71, 30)]


class Labels:
    """Gold labels of given patients, lazily; with ``split``, of the patients of this split only."""

    def __init__(self, t: Tables, split: str | None = None):
        self.t, self.split = t, split

    @cached_property
    def cases(self) -> DataFrame:
        if self.split is None:
            return self.t.src_case
        own = splits.assign(self.t).where(F.col("split") == self.split).select(F.col("patient_id").alias("subject_id"))
        return durable(self.t.src_case.join(own, "subject_id", "left_semi"))  # every label starts here

    @cached_property
    def own(self) -> Tables:
        return self.t if self.split is None else self.t.narrowed(self.cases)

    @cached_property
    def case_dx(self) -> DataFrame:
        return self.own.case_dx if self.split is None else durable(self.own.case_dx)

    @cached_property
    def case_finding(self) -> DataFrame:
        return self.own.case_finding if self.split is None else durable(self.own.case_finding)

    @cached_property
    def patient_dx(self) -> DataFrame:
        """Primary diagnoses of a patient's encounters with their greatest severity weight."""
        rows = self.cases.join(self.case_dx.where("role = 'primary'"), "case_id")
        return rows.groupBy(F.col("subject_id").alias("patient_id"), "dx_id").agg(F.max(severity()).alias("weight"), F.min("acuity").alias("acuity"))

    @cached_property
    def documented(self) -> DataFrame:
        return self.cases.join(self.case_dx, "case_id").select(F.col("subject_id").alias("patient_id"), "dx_id").distinct()

    @cached_property
    def chart_finding(self) -> DataFrame:
        rows = self.cases.join(self.case_finding, "case_id")
        return rows.groupBy(F.col("subject_id").alias("patient_id"), "finding_id").agg(F.max("relevance").alias("relevance"))

    @cached_property
    def key_finding(self) -> DataFrame:
        return self.chart_finding.where("relevance = 3").select("patient_id", "finding_id")

    @cached_property
    def query_dx(self) -> DataFrame:
        """The most severe primary diagnosis, the smallest id on ties. [D]"""
        first = F.row_number().over(Window.partitionBy("patient_id").orderBy(F.desc("weight"), "dx_id"))
        return self.patient_dx.withColumn("_r", first).where("_r = 1").select("patient_id", "dx_id")

    @cached_property
    def section_grade(self) -> DataFrame:
        """Grade 0-3 of every chart section for its patient's query diagnosis. [D]"""
        t = self.t
        rows = self.query_dx.join(self.cases.select("case_id", F.col("subject_id").alias("patient_id")), "patient_id").join(self.case_finding, "case_id").join(t.finding_node.select("finding_id", "kind"), "finding_id")
        rows = rows.join(t.dx_finding.select("dx_id", "finding_id", F.col("grade").alias("edge")), ["dx_id", "finding_id"], "left")
        g = F.when(F.col("edge").isNull(), 0).when((F.col("relevance") == 3) & (F.col("edge") == 3), 3).when(F.col("relevance") >= 2, 2).otherwise(1)
        return rows.groupBy("patient_id", (F.col("case_id") * 10 + kind_ord("kind")).alias("section_id")).agg(F.max(g).alias("grade"))

    @cached_property
    def imaging_gold(self) -> DataFrame:
        t = self.t
        own = self.cases.select("case_id")
        img = self.case_finding.join(own, "case_id", "left_semi").join(t.finding_node.where("kind = 'imaging'").select("finding_id"), "finding_id").select(F.col("case_id").alias("instance_id"), F.col("finding_id").alias("concept"))
        dx = self.case_dx.where("role = 'primary'").join(img.select(F.col("instance_id").alias("case_id")).distinct(), "case_id", "left_semi")
        return img.unionByName(dx.select(F.col("case_id").alias("instance_id"), (F.lit(1000000000) + F.col("dx_id")).alias("concept"))).distinct()

    @cached_property
    def dx_site(self) -> DataFrame:
        return links.dx_site(self.t)

    @cached_property
    def dx_alike(self) -> DataFrame:
        return links.alike(self.t)

    def heads(self, mine: DataFrame) -> DataFrame:
        """(patient_id, dx_id, specialty): the specialties of a patient's diagnoses, and of those of the patient's diagnoses that are linked to them.

        Links of one category lead to the diagnosis' own specialty; those of one site go through the patient's sites; only the others are pairs.
        """
        node = F.broadcast(self.t.dx_node.select(F.col("dx_id").alias("head"), F.col("category").alias("specialty")))
        of = lambda rows: rows.join(node, "head")
        own = of(mine.withColumn("head", F.col("dx_id"))).select("patient_id", "dx_id", "specialty")
        placed = mine.join(F.broadcast(self.dx_site), "dx_id")
        there = of(placed.withColumnRenamed("dx_id", "head")).select("patient_id", "site", "specialty").distinct()
        site = placed.join(there, ["patient_id", "site"]).select("patient_id", "dx_id", "specialty")
        pairs = self.dx_alike.unionByName(links.curated(self.t)).unionByName(links.several(self.t)).distinct()
        some = mine.join(pairs.select(F.explode(F.array("a", "b")).alias("dx_id")).distinct(), "dx_id", "left_semi")
        # A patient's own pairs of diagnoses that are linked; each patient has few diagnoses.
        both = some.select("patient_id", F.col("dx_id").alias("a")).join(some.select("patient_id", F.col("dx_id").alias("b")), "patient_id").where("a < b").join(pairs, ["a", "b"], "left_semi")
        both = both.select("patient_id", F.explode(F.array(F.struct(F.col("a").alias("dx_id"), F.col("b").alias("head")), F.struct(F.col("b").alias("dx_id"), F.col("a").alias("head")))).alias("x")).select("patient_id", "x.*")
        return own.unionByName(site).unionByName(of(both).select("patient_id", "dx_id", "specialty")).distinct()

    @cached_property
    def spec_rows(self) -> DataFrame:
        """Findings of a patient that a specialty's (non-differential) diagnoses own, or a diagnosis of the patient that is linked to one of them."""
        dx = self.cases.select("case_id", F.col("subject_id").alias("patient_id")).join(self.case_dx.where("role <> 'differential'").select("case_id", "dx_id"), "case_id")
        owned = dx.join(self.case_finding.select("case_id", "finding_id"), "case_id").join(self.t.dx_finding.select("dx_id", "finding_id"), ["dx_id", "finding_id"]).select("patient_id", "dx_id", "finding_id").distinct()
        return self.heads(dx.select("patient_id", "dx_id").distinct()).join(owned, ["patient_id", "dx_id"]).select("patient_id", "specialty", "finding_id").distinct()

    @cached_property
    def spec_gold(self) -> DataFrame:
        return durable(self.spec_rows)  # instances, gold and predictions all start from this

    @cached_property
    def absent_specialty(self) -> DataFrame:
        return self.absent(self.spec_gold.select("patient_id", "specialty").distinct())

    def absent(self, own: DataFrame) -> DataFrame:
        """Two specialties without a finding for each patient: the gold answer is to abstain. [D]"""
        every = own.select("patient_id").distinct().crossJoin(F.broadcast(self.t.nation.select("n_nationkey", F.col("n_name").alias("specialty"))))
        rank = F.row_number().over(Window.partitionBy("patient_id").orderBy((F.col("patient_id") * 13 + F.col("n_nationkey") * 7) % 25, "n_nationkey"))
        return every.join(own, ["patient_id", "specialty"], "left_anti").withColumn("_r", rank).where("_r <= 2").select("patient_id", "specialty")

    @cached_property
    def spec_item(self) -> DataFrame:
        return self.spec_gold.select("patient_id", "specialty", F.lit(False).alias("absent")).distinct().unionByName(self.absent_specialty.withColumn("absent", F.lit(True)))


class Panel:
    """Predictions of the simulated systems: integer arithmetic decides what is kept and what is noise."""

    def __init__(self, labels: Labels, most: int = len(PANEL)):
        self.l = labels
        self.systems = F.broadcast(labels.t.spark.createDataFrame(PANEL[:most], "m int, drops int, noise int"))

    @staticmethod
    def kept(item: str, key: str, more: int = 0):
        return (F.col(item) * 31 + F.col(key) * 17 + F.col("m") * 13) % 100 >= F.col("drops") + more

    @staticmethod
    def spurious(item: str, key: str, times: int = 1):
        return (F.col(item) * 29 + F.col(key) * 19 + F.col("m") * 7) % 100 < F.col("noise") * times

    @cached_property
    def dx(self) -> DataFrame:
        g, d, s = self.l.patient_dx, self.l.documented, self.systems
        n = self.l.t.supplier.agg(F.count("*").alias("_n"))
        off = g.select("patient_id").distinct().crossJoin(s).crossJoin(F.broadcast(n)).withColumn("_k", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))))
        off = off.withColumn("dx_id", 1 + (F.col("patient_id") * 7 + F.col("m") * 5 + F.col("_k") * 13) % F.col("_n")).drop("_k", "_n", "drops").distinct()
        parts = [
            g.crossJoin(s).where(self.kept("dx_id", "patient_id")),
            d.join(g, ["patient_id", "dx_id"], "left_anti").crossJoin(s).where(self.spurious("dx_id", "patient_id")),
            off.join(d, ["patient_id", "dx_id"], "left_anti").where(self.spurious("dx_id", "patient_id", 2)),
        ]
        return parts[0].select("m", "patient_id", "dx_id").unionByName(parts[1].select("m", "patient_id", "dx_id")).unionByName(parts[2].select("m", "patient_id", "dx_id"))

    @cached_property
    def finding(self) -> DataFrame:
        keep = (F.col("relevance") == 3) & self.kept("finding_id", "patient_id", 15) | (F.col("relevance") < 3) & self.spurious("finding_id", "patient_id", 2)
        return self.l.chart_finding.crossJoin(self.systems).where(keep).select("m", "patient_id", "finding_id")

    @cached_property
    def ranked(self) -> DataFrame:
        rows = self.l.section_grade.crossJoin(self.systems)
        est = F.when(self.kept("section_id", "patient_id"), F.col("grade")).otherwise((F.col("section_id") + F.col("m")) % 4)
        tie = (F.col("section_id") * 37 + F.col("patient_id") * 11 + F.col("m") * 3) % 101
        order = Window.partitionBy("m", "patient_id").orderBy(F.desc(est), tie, "section_id")
        return rows.select("m", "patient_id", "section_id", F.row_number().over(order).cast("long").alias("rank"))

    @cached_property
    def imaging(self) -> DataFrame:
        g, t = self.l.imaging_gold, self.l.t
        kept = g.crossJoin(self.systems).where(self.kept("concept", "instance_id", 12)).select("m", "instance_id", "concept")
        other = self.l.case_finding.join(t.finding_node.where("kind <> 'imaging'").select("finding_id"), "finding_id").select(F.col("case_id").alias("instance_id"), F.col("finding_id").alias("concept"))
        other = other.join(g.select("instance_id").distinct(), "instance_id", "left_semi").crossJoin(self.systems).where(self.spurious("concept", "instance_id"))
        return kept.unionByName(other.select("m", "instance_id", "concept").distinct())

    @cached_property
    def specialty(self) -> DataFrame:
        kept = self.l.spec_gold.crossJoin(self.systems).where(self.kept("finding_id", "patient_id", 5)).select("m", "patient_id", "specialty", "finding_id")
        made = self.l.absent_specialty.crossJoin(self.systems).where((F.col("patient_id") * 29 + F.col("m") * 7 + F.length("specialty")) % 100 < F.col("noise") * 2)
        return kept.unionByName(made.select("m", "patient_id", "specialty", (1 + (F.col("patient_id") * 3 + F.col("m")) % 7).alias("finding_id")))
