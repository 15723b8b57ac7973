"""Task instances with the number of their gold items, counted for one slice of patients after another.

A slice holds all cases of its patients, so the counts are those of all patients at once; the disk holds the joins of one slice at a time.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.checkpoint import Packed, clear, drop
from ..sources.tables import Tables
from . import links, splits
from .labels import Labels

#: Rows of lineitem for each slice.
ROWS = 5_000_000
LINES = ("l_orderkey", "l_partkey", "l_suppkey", "l_extendedprice", "l_returnflag", "l_linestatus")


class _Dealt(Tables):
    """Lines dealt out by diagnosis and finding, so that both steps of a distinct count need one shuffle."""

    @property
    def lineitem(self) -> DataFrame:
        return super().__getattr__("lineitem").select("l_suppkey", "l_partkey", "l_orderkey", "l_returnflag").repartition("l_suppkey", "l_partkey")


class _Slice(Tables):
    """The views over some patients' cases and lines, beside the links of all."""

    def __init__(self, t: Tables, cases: DataFrame, lines: DataFrame, dx_finding: DataFrame):
        super().__init__(t.spark, t.sf_dir)
        self.src_case, self.lines, self.dx_finding = cases, lines, dx_finding

    @property
    def case_lines(self) -> DataFrame:
        return self.lines


def counts(t: Tables, split: str | None = None, rows: int = ROWS) -> dict[str, DataFrame]:
    """Of each task, and of specialties to abstain on, the instances with ``n_gold``; ``case``: the cases; ``profile``: of all patients, that of ``splits``."""
    n = max(1, -(-t.lineitem.count() // rows))
    edges = Packed(_Dealt(t.spark, t.sf_dir).dx_finding)
    clear(t.spark)
    known = Tables(t.spark, t.sf_dir)
    known.dx_finding = edges.df
    site, alike = Packed(links.dx_site(known)), Packed(links.alike(known))
    clear(t.spark)
    slice_of = F.pmod(F.xxhash64("subject_id"), F.lit(n)).cast("int").alias("slice")
    cases = Packed(Labels(t, split).cases.select("case_id", "subject_id", "acuity", slice_of), "slice")
    at = cases.df.select(F.col("case_id").alias("l_orderkey"), "slice").distinct()
    lines = Packed(t.lineitem.select(*LINES).join(at, "l_orderkey"), "slice")
    clear(t.spark)
    out: dict[str, list[DataFrame]] = {}
    for k in range(n):
        own = lambda x, k=k: x.df.where(F.col("slice") == k).drop("slice")
        s = _Slice(t, own(cases), own(lines), edges.df)
        views = Packed(s.case_dx), Packed(s.case_finding)
        s.case_dx, s.case_finding = (v.df for v in views)
        g = Labels(s)
        g.dx_site, g.dx_alike = site.df, alike.df
        per = lambda f, *keys: f.groupBy("patient_id", *keys).agg(F.count("*").alias("n_gold"))
        patient = g.cases.select(F.col("case_id").alias("instance_id"), F.col("subject_id").alias("patient_id"))
        parts = {
            "diagnosis": lambda g=g: per(g.patient_dx),
            "summarization": lambda g=g: per(g.key_finding),
            "retrieval": lambda g=g: g.section_grade.groupBy("patient_id").agg(F.count_if(F.col("grade") >= 2).alias("n_gold")),
            "specialty": lambda g=g: per(g.spec_rows, "specialty"),
            "absent": lambda g=g: g.absent(out["specialty"][-1].select("patient_id", "specialty")).withColumn("n_gold", F.lit(0).cast("long")),
            "imaging": lambda g=g, p=patient: g.imaging_gold.groupBy("instance_id").agg(F.count("*").alias("n_gold")).join(p, "instance_id"),
        }
        if split is None:
            parts["profile"] = lambda s=s: splits.profile(s)
        for name, part in parts.items():
            out.setdefault(name, []).append(Packed(part()).df)
            clear(t.spark)
        drop(*views)
    drop(edges, site, alike, lines)
    return {name: reduce(lambda a, b: a.unionByName(b), fs) for name, fs in out.items()} | {"case": cases.df.drop("slice")}


def of(t: Tables, split: str | None = None, named: bool = False, rows: int = ROWS) -> DataFrame:
    """(task, instance_id, patient_id, encounters, n_gold): each instance names its patient and source cases, with ``named`` its split, too; the gold itself stays in the label views."""
    n = counts(t, split, rows)
    cases = n["case"].groupBy(F.col("subject_id").alias("patient_id")).agg(F.array_join(F.array_sort(F.collect_list("case_id")), ",").alias("encounters"))
    image = n["imaging"]
    if named:
        split_of = splits.assign(t, n["profile"]).select("patient_id", "split")
        cases, image = cases.join(split_of, "patient_id"), image.join(split_of, "patient_id")
    name = lambda *c: F.concat(*[x for k, v in enumerate(c) for x in ([F.lit(":")] if k else []) + [v]])
    text = lambda c: F.col(c).cast("string")
    cols = ["task", "instance_id", "patient_id", "encounters", "n_gold"] + ["split"] * named
    out = [n[k].join(cases, "patient_id").withColumns({"task": F.lit(k), "instance_id": name(F.lit(k), text("patient_id"))}) for k in ("diagnosis", "summarization", "retrieval")]
    spec = n["specialty"].unionByName(n["absent"]).join(cases, "patient_id")
    out.append(spec.withColumns({"task": F.lit("specialty"), "instance_id": name(F.lit("specialty"), text("patient_id"), F.col("specialty"))}))
    out.append(image.withColumns({"task": F.lit("imaging"), "encounters": text("instance_id"), "instance_id": name(F.lit("imaging"), text("instance_id"))}))
    return reduce(lambda a, b: a.unionByName(b), (f.select(cols) for f in out))
