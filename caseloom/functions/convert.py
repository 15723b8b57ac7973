"""Conversion of foreign records to the house schema by fixed rules; the prose itself stays as it is.

All rules are column expressions, so a note is converted where it is read; only the joins of notes,
visits and reports of one case shuffle.  The text names no section types or tables but a few, so
those below are ours [D].  Null texts are empty; sections without a body give no row.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.checkpoint import durable

# Section types in order.
SECTIONS = (
    "demographics", "chief_complaint", "allergies", "present_illness", "past_history", "past_surgery", "family_history", "social_history", "home_medications",
    "vital_signs", "examination", "laboratory", "imaging", "procedures", "hospital_course", "discharge_medications", "assessment_plan", "follow_up",
)
# Labels of foreign notes and their types.
LABELS = {
    "Chief Complaint": "chief_complaint",
    "Allergies": "allergies",
    "History of Present Illness": "present_illness",
    "Past Medical History": "past_history",
    "Past Surgical History": "past_surgery",
    "Family History": "family_history",
    "Social History": "social_history",
    "Medications on Admission": "home_medications",
    "Vitals": "vital_signs",
    "Physical Exam": "examination",
    "Pertinent Results": "laboratory",
    "Imaging": "imaging",
    "Major Surgical or Invasive Procedure": "procedures",
    "Brief Hospital Course": "hospital_course",
    "Discharge Medications": "discharge_medications",
    "Discharge Diagnosis": "assessment_plan",
    "Discharge Instructions": "follow_up",
    "Followup Instructions": "follow_up",
}
# Abbreviations of laboratory tests with name, unit and reference range.
LABS = {
    "WBC": ("White blood cell count", "thousand per microlitre", "4.0-11.0"),
    "RBC": ("Red blood cell count", "million per microlitre", "4.2-5.9"),
    "Hgb": ("Haemoglobin", "g/dL", "12.0-17.5"),
    "Hct": ("Haematocrit", "%", "36-50"),
    "Plt": ("Platelet count", "thousand per microlitre", "150-400"),
    "Na": ("Sodium", "mmol/L", "135-145"),
    "K": ("Potassium", "mmol/L", "3.5-5.0"),
    "Cl": ("Chloride", "mmol/L", "98-107"),
    "HCO3": ("Bicarbonate", "mmol/L", "22-29"),
    "UreaN": ("Urea nitrogen", "mg/dL", "7-20"),
    "Creat": ("Creatinine", "mg/dL", "0.6-1.3"),
    "Glucose": ("Glucose", "mg/dL", "70-100"),
}
# Codes in medication lines.
CODES = {
    "PO": "by mouth", "IV": "intravenously", "SC": "under the skin", "DAILY": "once daily", "BID": "twice daily", "TID": "three times daily", "QID": "four times daily",
    "QHS": "at bedtime", "QAM": "every morning", "Q4H": "every 4 hours", "Q6H": "every 6 hours", "Q8H": "every 8 hours", "Q12H": "every 12 hours", "PRN": "as needed",
}
# Patterns of vital signs and their sentences.
VITALS = (
    (r"\bT(?:emp)?[ :]+([0-9]{2,3}(?:\.[0-9]+)?)\b", "Temperature", "degrees Fahrenheit."),
    (r"\b(?:HR|P)[ :]+([0-9]{2,3})\b", "Heart rate", "per minute."),
    (r"\bBP[ :]+([0-9]{2,3}/[0-9]{2,3})\b", "Blood pressure", "mmHg."),
    (r"\bRR[ :]+([0-9]{1,2})\b", "Respiratory rate", "per minute."),
    (r"\b(?:O2|SpO2|Sat)[ :]+([0-9]{2,3}%)", "Oxygen saturation", "on room air."),
)
# Fictional names of providers.
NAMES = ("Adler", "Brook", "Cole", "Dane", "Ellis", "Frost", "Grant")

LO, HI = "2020-01-01", "2024-12-31"
_DATE = r"\b[0-9]{4}-[0-9]{2}-[0-9]{2}\b"
_LABEL = "(?:" + "|".join(re.escape(x) for x in LABELS) + ")"


def _lookup(values: dict, key: Column) -> Column:
    return F.try_element_at(F.create_map(*[F.lit(x) for kv in values.items() for x in kv]), key)


def offsets(visits: DataFrame, lo: str = LO, hi: str = HI) -> DataFrame:
    """(subject_id, shift): the days that move all visits of a subject, intervals kept, into the window.

    The first visit comes to a place in the slack that depends on the id.  A history longer than the
    window starts at ``lo``; its visits after ``hi`` are not inside (see ``shifted``).
    """
    span = visits.groupBy("subject_id").agg(F.min(F.to_date("recorded_at")).alias("a"), F.max(F.to_date("recorded_at")).alias("z"))
    first, last = F.lit(lo).cast("date"), F.lit(hi).cast("date")
    slack = F.greatest(F.lit(0), F.datediff(last, first) - F.datediff("z", "a"))
    return span.select("subject_id", (F.datediff(first, "a") + F.pmod(F.col("subject_id") * 7919, slack + 1)).cast("int").alias("shift"))


def shifted(visits: DataFrame, lo: str = LO, hi: str = HI) -> DataFrame:
    """Visits with their shift, new date and whether that is inside the window."""
    out = visits.join(offsets(visits, lo, hi), "subject_id").withColumn("visited", F.date_add(F.to_date("recorded_at"), F.col("shift")))
    return out.withColumn("inside", F.col("visited") <= F.lit(hi).cast("date"))


def shift_text(text: Column, shift: Column) -> Column:
    """The dates in a text, moved as the visits are; what is no date of the calendar stays."""
    dates = F.transform(F.regexp_extract_all(text, F.lit(_DATE), F.lit(0)), lambda x: F.coalesce(F.date_add(x.try_cast("date"), shift).cast("string"), x))
    return F.array_join(F.zip_with(F.split(text, _DATE, -1), dates, lambda p, x: F.concat(p, F.coalesce(x, F.lit("")))), "")


def provider(subject: Column) -> Column:
    """One name for the masked providers of a subject."""
    return F.element_at(F.array(*[F.lit(x) for x in NAMES]), (F.pmod(subject * 31 + 7, F.lit(len(NAMES))) + 1).cast("int"))


def unmask(text: Column, subject: Column) -> Column:
    """Masks repaired: providers get a name, clauses with a masked subject go, as do masked objects of prepositions [D]."""
    named = F.regexp_replace(text, F.lit(r"\bDr\.? ___"), F.concat(F.lit("Dr. "), provider(subject)))
    kept = F.regexp_replace(named, r"(?m)(?<=^|[.;:] )___ (?:[^.;\n]|[.](?=\S))*(?:[.;] ?|$)", "")
    return F.regexp_replace(kept, r" (?:at|by|from|in|of|on|to|with) ___", "")


def sections(text: Column) -> Column:
    """The parts of a note as array of (label, body); text before the first label has the label ''."""
    parts = F.split(F.coalesce(text, F.lit("")), rf"(?m)^(?={_LABEL}:)")
    label = rf"^({_LABEL}):"
    return F.transform(parts, lambda p: F.struct(F.regexp_extract(p, label, 1).alias("label"), F.trim(F.regexp_replace(p, rf"{label}[ \t]*", ""), F.lit(" \n\r\t")).alias("body")))


def _by_line(body: Column, line) -> Column:
    return F.array_join(F.transform(F.split(body, "\n"), line), "\n")


def expand_labs(body: Column) -> Column:
    """Panel lines (``Na-140 K-4.1``) as a line for each test with name, unit and range; other lines and unknown tests stay."""
    value = lambda tok: F.regexp_extract(tok, r"^[A-Za-z0-9]+-([0-9.]+\*?)$", 1)
    name, tail = {k: v[0] for k, v in LABS.items()}, {k: f" {v[1]} (reference {v[2]})" for k, v in LABS.items()}

    def test(tok: Column) -> Column:
        key = F.substring_index(tok, "-", 1)
        return F.coalesce(F.concat(_lookup(name, key), F.lit(": "), value(tok), _lookup(tail, key)), tok)

    panel = lambda x: F.array_join(F.transform(F.filter(F.split(x, r"\s+"), lambda tok: tok != ""), test), "\n")
    return _by_line(body, lambda x: F.when(x.rlike(r"^\s*+(?:[A-Za-z0-9]++-[0-9.]++\*?+(?:\s++|$))+$"), panel(x)).otherwise(x))


def expand_meds(body: Column) -> Column:
    """Codes in words, mixed-case drug names in lower case."""
    mixed = r"^(?:[a-z]{2,}[A-Z]{2,}[a-z]*|[A-Z]{2,}[a-z]{3,})$"
    word = lambda x: F.coalesce(_lookup(CODES, x), F.when(x.rlike(mixed), F.lower(x)).otherwise(x))
    return _by_line(body, lambda x: F.array_join(F.transform(F.split(x, " "), word), " "))


def vitals(body: Column) -> Column:
    """Vital signs as sentences, in a fixed order; what else stands there follows."""
    said, rest = [], body
    for pattern, name, unit in VITALS:
        v = F.regexp_extract(body, pattern, 1)
        said.append(F.when(v != "", F.concat(F.lit(f"{name} "), v, F.lit(f" {unit}"))))
        rest = F.regexp_replace(rest, pattern, "")
    rest = F.trim(F.regexp_replace(rest, r"[ \t]+", " "))
    return F.concat_ws(" ", *said, F.when(rest != "", rest))


def impression(text: Column) -> Column:
    """The impression of a report; a report without one stays whole."""
    part = F.trim(F.regexp_extract(text, r"(?s)\bIMPRESSION:\s*(.*)$", 1), F.lit(" \n\r\t"))
    return F.when(part != "", part).otherwise(text)


def normalize(notes: DataFrame, visits: DataFrame, reports: DataFrame, lo: str = LO, hi: str = HI) -> DataFrame:
    """Charts in the house schema: (subject_id, case_id, visited, ord, stype, body).

    ``notes`` (case_id, text), ``visits`` (case_id, subject_id, recorded_at, age_years, sex, setting) and ``reports`` (case_id, report_id, text)
    are one hospital's records.  Parts of one type in a note come together, in order; the text before the first label joins the demographics.
    """
    seen = shifted(visits, lo, hi).where("inside")
    read = reports.select("case_id", F.struct("report_id", impression(F.coalesce("text", F.lit(""))).alias("body")).alias("r")).groupBy("case_id")
    read = read.agg(F.array_join(F.filter(F.transform(F.array_sort(F.collect_list("r")), lambda x: x["body"]), lambda x: x != ""), "\n").alias("_reports"))
    rows = seen.join(notes.select("case_id", "text"), "case_id", "left").join(read, "case_id", "left")
    repaired = lambda c: shift_text(unmask(F.coalesce(c, F.lit("")), F.col("subject_id")), F.col("shift"))
    who = F.concat(F.col("age_years").cast("string"), F.lit("-year-old "), F.when(F.col("sex") == "F", "woman").otherwise("man"), F.lit(", "), F.lower("setting"), F.lit("."))
    rows = rows.select("subject_id", "case_id", "visited", who.alias("_who"), repaired(F.col("_reports")).alias("_reports"), sections(repaired(F.col("text"))).alias("_parts"))
    typed = F.transform("_parts", lambda p: F.struct(F.coalesce(_lookup(LABELS, p["label"]), F.lit(SECTIONS[0])).alias("stype"), p["body"].alias("body")))
    extra = F.array(F.struct(F.lit(SECTIONS[0]).alias("stype"), F.col("_who").alias("body")), F.struct(F.lit("imaging").alias("stype"), F.coalesce("_reports", F.lit("")).alias("body")))
    rows = rows.withColumn("_parts", F.filter(F.concat(extra, typed), lambda p: p["body"] != ""))
    order = F.array(*[F.struct(F.lit(i).alias("ord"), F.lit(s).alias("stype")) for i, s in enumerate(SECTIONS, 1)])
    joined = lambda s: F.array_join(F.transform(F.filter("_parts", lambda p: p["stype"] == s), lambda p: p["body"]), "\n")
    present = F.filter(order, lambda o: F.exists("_parts", lambda p: p["stype"] == o["stype"]))
    flat = rows.withColumn("_s", F.explode(present)).select("subject_id", "case_id", "visited", "_s.ord", "_s.stype", joined(F.col("_s.stype")).alias("body"))
    s, b = F.col("stype"), F.col("body")
    shown = F.when(s == "laboratory", expand_labs(b)).when(s.isin("home_medications", "discharge_medications"), expand_meds(b)).when(s == "vital_signs", vitals(b)).otherwise(b)
    return flat.withColumn("body", shown)


def harmonize(real: DataFrame, synthetic: DataFrame, budget: int | None = None) -> DataFrame:
    """Both arms, (arm, subject_id, case_id, visited, ord, stype, body), alike in sections and length.

    Section types of one arm alone go, and so do the last visits of a chart from the first that passes the budget (characters).  Without a budget it
    is the smaller of the arms' median chart lengths [D].  A chart keeps its first visit.  Both arms are checkpointed, as they are read several times.
    """
    cols = ["subject_id", "case_id", "visited", "ord", "stype", "body"]
    both = durable(real.select(F.lit("real").alias("arm"), *cols).unionByName(synthetic.select(F.lit("synthetic").alias("arm"), *cols)))
    shared = both.groupBy("stype").agg(F.min("arm").alias("a"), F.max("arm").alias("z")).where("a <> z").select("stype")
    kept = both.join(F.broadcast(shared), "stype", "left_semi")  # at most as many rows as section types
    size = kept.groupBy("arm", "subject_id", "case_id", "visited").agg(F.sum(F.length("body")).alias("n"))
    w = Window.partitionBy("arm", "subject_id").orderBy("visited", "case_id")
    run = size.select("arm", "subject_id", "case_id", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"), F.row_number().over(w).alias("k"))
    if budget is None:
        chart = size.groupBy("arm", "subject_id").agg(F.sum("n").alias("n")).groupBy("arm").agg(F.percentile("n", 0.5).alias("m"))
        run = run.crossJoin(F.broadcast(chart.agg(F.min("m").alias("most"))))  # one row
    else:
        run = run.withColumn("most", F.lit(float(budget)))
    return kept.join(run.where("k = 1 OR run <= most").select("arm", "case_id"), ["arm", "case_id"], "left_semi").select("arm", *cols)
