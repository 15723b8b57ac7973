"""Registered queries: conversion of foreign records, whole and by rule, and harmonization of both arms.

The twins build the expected charts from the tables and never see a foreign note.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import convert as C
from ..plans.oracle import VIEWS, sql
from ..sources import foreign as X
from ..sources.tables import Tables
from .registry import register

VIEWS["visit_date"] = """
    SELECT case_id, subject_id, age_years, sex, setting, CAST(recorded_at AS DATE) + CAST(sh AS INTEGER) AS visited
    FROM src_case JOIN (
        SELECT subject_id, date_diff('day', a, DATE '2020-01-01') + (subject_id * 7919) % (greatest(0, 1826 - date_diff('day', a, z)) + 1) AS sh
        FROM (SELECT subject_id, min(CAST(recorded_at AS DATE)) AS a, max(CAST(recorded_at AS DATE)) AS z FROM src_case GROUP BY 1)
    ) USING (subject_id)"""
VIEWS["foreign_body"] = """
    SELECT v.*, (subject_id * 31 + 7) % 7 AS who, CAST(recorded_at AS DATE) + 55000 AS ahead, symptom, sign, lab, imaging, medication, history
    FROM visit_date v JOIN (SELECT case_id, recorded_at FROM src_case) USING (case_id) LEFT JOIN (
        SELECT case_id, max(body) FILTER (WHERE stype = 'symptom') AS symptom, max(body) FILTER (WHERE stype = 'sign') AS sign, max(body) FILTER (WHERE stype = 'lab') AS lab,
            max(body) FILTER (WHERE stype = 'imaging') AS imaging, max(body) FILTER (WHERE stype = 'medication') AS medication, max(body) FILTER (WHERE stype = 'history') AS history
        FROM chart_section GROUP BY 1
    ) USING (case_id) WHERE subject_id % 2 = 1"""
WHO = "CASE who WHEN 0 THEN 'Adler' WHEN 1 THEN 'Brook' WHEN 2 THEN 'Cole' WHEN 3 THEN 'Dane' WHEN 4 THEN 'Ellis' WHEN 5 THEN 'Frost' ELSE 'Grant' END"
LAB = "'Sodium: ' || (130 + case_id % 20) || ' mmol/L (reference 135-145)' || chr(10) || 'Potassium: ' || (3 + case_id % 3) || '.5* mmol/L (reference 3.5-5.0)' || chr(10) || 'Lipase-' || (20 + case_id % 9) || chr(10) || lab"
MEDS = "array_to_string(list_transform(string_split(medication, '; '), lambda x: replace(x, ' ', '') || ' 10 mg by mouth twice daily'), chr(10))"
SIGNS = "'Temperature ' || (96 + case_id * 3 % 5) || '.4 degrees Fahrenheit. Heart rate ' || (60 + case_id * 7 % 50) || ' per minute. Blood pressure ' || (100 + case_id * 11 % 40) || '/' || (60 + case_id * 5 % 30) || ' mmHg. Respiratory rate ' || (12 + case_id % 9) || ' per minute.'"
PARTS = [
    ("age_years || '-year-old ' || CASE sex WHEN 'F' THEN 'woman' ELSE 'man' END || ', ' || lower(setting) || '.'", "demographics"),
    ("symptom", "chief_complaint"),
    ("'none known'", "allergies"),
    (f"'Admitted on ' || CAST(visited AS VARCHAR) || '. Seen by Dr. ' || {WHO} || '. Course as below.'", "present_illness"),
    ("history", "past_history"),
    (SIGNS, "vital_signs"),
    ("sign", "examination"),
    (LAB, "laboratory"),
    ("imaging", "imaging"),
    (MEDS, "discharge_medications"),
    ("'stable'", "assessment_plan"),
    ("'Return on ' || CAST(visited + 14 AS VARCHAR) || '.'", "follow_up"),
]
VIEWS["converted"] = " UNION ALL ".join(
    f"SELECT subject_id, case_id, visited, {C.SECTIONS.index(s) + 1} AS ord, '{s}' AS stype, {b} AS body FROM foreign_body WHERE visited <= DATE '2024-12-31' AND ({b}) IS NOT NULL" for b, s in PARTS
)
VIEWS["house_chart"] = (
    "SELECT subject_id, case_id, CAST(recorded_at AS DATE) AS visited, s.stype, s.body FROM src_case JOIN ("
    + " UNION ALL ".join(f"SELECT case_id, '{s}' AS stype, body FROM chart_section WHERE stype = '{k}'" for k, s in X.HOUSE.items())
    + " UNION ALL SELECT case_id, 'social_history' AS stype, 'lives alone' AS body FROM src_case) s USING (case_id) WHERE subject_id % 2 = 0"
)
VIEWS["both_arms"] = "SELECT 'real' AS arm, subject_id, case_id, visited, stype, body FROM converted UNION ALL SELECT 'synthetic' AS arm, subject_id, case_id, visited, stype, body FROM house_chart"
VIEWS["arm_kept"] = "SELECT * FROM both_arms WHERE stype IN (SELECT stype FROM both_arms GROUP BY 1 HAVING count(DISTINCT arm) = 2)"
VIEWS["arm_size"] = "SELECT arm, subject_id, case_id, visited, sum(length(body)) AS n FROM arm_kept GROUP BY ALL"
VIEWS["arm_budget"] = "SELECT min(m) AS most FROM (SELECT arm, quantile_cont(n, 0.5) AS m FROM (SELECT arm, subject_id, sum(n) AS n FROM arm_size GROUP BY 1, 2) GROUP BY 1)"
VIEWS["arm_visit"] = """
    SELECT arm, case_id FROM (
        SELECT arm, case_id, sum(n) OVER w AS run, row_number() OVER w AS k FROM arm_size
        WINDOW w AS (PARTITION BY arm, subject_id ORDER BY visited, case_id ROWS UNBOUNDED PRECEDING)
    ), arm_budget WHERE k = 1 OR run <= most"""


def q(key, fn, text):
    register(key, lambda spark, sf: fn(Tables(spark, sf)), sql(text))


def converted(t):
    return C.normalize(X.notes(t), X.visits(t), X.reports(t))


def parts(t):
    """(case_id, place, label, body) of the foreign notes."""
    return X.notes(t).select("case_id", F.posexplode(C.sections(F.col("text"))).alias("place", "p")).select("case_id", "place", "p.label", "p.body")


def labelled(t, label):
    return parts(t).where(F.col("label") == label)


def arms(t):
    return C.harmonize(converted(t), X.house(t))


def dated(f):
    return f.withColumn("visited", F.col("visited").cast("string"))


q("q_convert_all", lambda t: dated(converted(t)), "SELECT subject_id, case_id, CAST(visited AS VARCHAR) AS visited, ord, stype, body FROM converted")

FOUND = [("Allergies", "TRUE"), ("Chief Complaint", "symptom IS NOT NULL"), ("History of Present Illness", "TRUE"), ("Past Medical History", "history IS NOT NULL"), ("Vitals", "TRUE"), ("Physical Exam", "sign IS NOT NULL")]
FOUND += [("Pertinent Results", "lab IS NOT NULL"), ("Discharge Medications", "medication IS NOT NULL"), ("Discharge Diagnosis", "TRUE"), ("Followup Instructions", "TRUE")]
q(
    "q_convert_sections",
    lambda t: parts(t).select("case_id", "place", "label"),
    "SELECT case_id, CAST(row_number() OVER (PARTITION BY case_id ORDER BY o) - 1 AS INTEGER) AS place, label FROM ("
    + " UNION ALL ".join(f"SELECT case_id, {i} AS o, '{x}' AS label FROM foreign_body WHERE {c}" for i, (x, c) in enumerate(FOUND))
    + ")",
)
q("q_shift_dates", lambda t: dated(C.shifted(t.src_case)).select("case_id", "visited", "inside"), "SELECT case_id, CAST(visited AS VARCHAR) AS visited, visited <= DATE '2024-12-31' AS inside FROM visit_date")
q(
    "q_unmask",
    lambda t: labelled(t, "History of Present Illness").join(X.visits(t).select("case_id", "subject_id"), "case_id").select("case_id", C.unmask(F.col("body"), F.col("subject_id")).alias("body")),
    f"SELECT case_id, 'Admitted on ' || CAST(ahead AS VARCHAR) || '. Seen by Dr. ' || {WHO} || '. Course as below.' AS body FROM foreign_body",
)
q("q_expand_labs", lambda t: labelled(t, "Pertinent Results").select("case_id", C.expand_labs(F.col("body")).alias("body")), f"SELECT case_id, {LAB} AS body FROM foreign_body WHERE lab IS NOT NULL")
q("q_expand_meds", lambda t: labelled(t, "Discharge Medications").select("case_id", C.expand_meds(F.col("body")).alias("body")), f"SELECT case_id, {MEDS} AS body FROM foreign_body WHERE medication IS NOT NULL")
q("q_vitals_sentence", lambda t: labelled(t, "Vitals").select("case_id", C.vitals(F.col("body")).alias("body")), f"SELECT case_id, {SIGNS} AS body FROM foreign_body")
q("q_impression", lambda t: X.reports(t).select("case_id", C.impression(F.col("text")).alias("body")), "SELECT case_id, imaging AS body FROM foreign_body WHERE imaging IS NOT NULL")
q("q_harmonize_sections", lambda t: arms(t).select("arm", "case_id", "stype"), "SELECT arm, case_id, stype FROM arm_kept JOIN arm_visit USING (arm, case_id)")
q("q_budget_truncate", lambda t: arms(t).select("arm", "case_id").distinct(), "SELECT arm, case_id FROM arm_visit")
