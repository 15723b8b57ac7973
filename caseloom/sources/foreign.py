"""Foreign hospital records, rendered from the given tables: subjects with odd ids are the foreign arm, the others the house's own.

Notes carry labels, masks, a calendar 55,000 days ahead, panels, codes and mixed-case drug names,
as ``functions.convert`` has to repair them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tables import Tables

AHEAD = 55_000
#: The house's section type of each kind of finding.
HOUSE = {"symptom": "chief_complaint", "sign": "examination", "lab": "laboratory", "imaging": "imaging", "medication": "discharge_medications", "history": "past_history"}


def visits(t: Tables) -> DataFrame:
    return t.src_case.where("subject_id % 2 = 1").withColumn("recorded_at", F.date_add(F.to_date("recorded_at"), AHEAD))


def _bodies(t: Tables) -> DataFrame:
    return t.chart_section.groupBy("case_id").agg(F.map_from_entries(F.collect_list(F.struct("stype", "body"))).alias("m"))


def notes(t: Tables) -> DataFrame:
    """(case_id, text): a discharge note for each visit."""
    rows = visits(t).select("case_id", "recorded_at").join(_bodies(t), "case_id", "left")
    c, when = F.col("case_id"), F.col("recorded_at")
    of = lambda kind: F.try_element_at("m", F.lit(kind))
    drug = lambda x: F.concat(F.substring_index(x, " ", 1), F.upper(F.substring_index(x, " ", -1)), F.lit(" 10 mg PO BID"))
    n = lambda base, k, m: (F.lit(base) + F.pmod(c * k, F.lit(m))).cast("string")
    lines = [
        F.concat(F.lit("Allergies: none known")),
        F.concat(F.lit("Chief Complaint: "), of("symptom")),
        F.concat(F.lit("History of Present Illness: Admitted on "), when.cast("string"), F.lit(". Seen by Dr. ___ at ___. ___ was told of the 2.5 mg dose. Course as below.")),
        F.concat(F.lit("Past Medical History: "), of("history")),
        F.concat(F.lit("Vitals: T "), n(96, 3, 5), F.lit(".4 HR "), n(60, 7, 50), F.lit(" BP "), n(100, 11, 40), F.lit("/"), n(60, 5, 30), F.lit(" RR "), n(12, 1, 9)),
        F.concat(F.lit("Physical Exam:\n"), of("sign")),
        F.concat(F.lit("Pertinent Results:\nNa-"), n(130, 1, 20), F.lit(" K-"), n(3, 1, 3), F.lit(".5* Lipase-"), n(20, 1, 9), F.lit("\n"), of("lab")),
        F.concat(F.lit("Discharge Medications:\n"), F.array_join(F.transform(F.split(of("medication"), "; "), drug), "\n")),
        F.lit("Discharge Diagnosis: stable"),
        F.concat(F.lit("Followup Instructions: Return on "), F.date_add(when, 14).cast("string"), F.lit(".")),
    ]
    return rows.select("case_id", F.concat_ws("\n", *lines).alias("text"))


def reports(t: Tables) -> DataFrame:
    """(case_id, report_id, text): radiology reports of several paragraphs."""
    rows = t.chart_section.where("stype = 'imaging'").join(visits(t).select("case_id"), "case_id", "left_semi")
    return rows.select("case_id", F.col("section_id").alias("report_id"), F.concat(F.lit("EXAMINATION: two views\n\nFINDINGS: The film of ___ was reviewed.\n\nIMPRESSION: "), "body").alias("text"))


def house(t: Tables) -> DataFrame:
    """The house's own charts: (subject_id, case_id, visited, ord, stype, body)."""
    from ..functions.convert import SECTIONS

    rows = t.src_case.where("subject_id % 2 = 0").select("subject_id", "case_id", F.to_date("recorded_at").alias("visited"))
    name = F.create_map(*[F.lit(x) for kv in HOUSE.items() for x in kv])
    own = t.chart_section.where(F.col("stype").isin(*HOUSE)).select("case_id", F.element_at(name, F.col("stype")).alias("stype"), "body")
    own = rows.join(own, "case_id").unionByName(rows.withColumns({"stype": F.lit("social_history"), "body": F.lit("lives alone")}))
    place = F.array_position(F.array(*[F.lit(s) for s in SECTIONS]), F.col("stype")).cast("int")
    return own.select("subject_id", "case_id", "visited", place.alias("ord"), "stype", "body")
