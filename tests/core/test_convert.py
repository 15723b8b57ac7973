"""Rules of the conversion on small cases; the twins of whole charts are in test_queries."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from caseloom.functions import convert as C


def one(spark, text, f):
    return spark.createDataFrame([(text,)], "x string").select(f(F.col("x")).alias("y")).first()["y"]


def test_sections(spark):
    text = "Admitted from home.\nChief Complaint: pain\nno Allergies: here\nAllergies:\n\nVitals: T 98.6\nChief Complaint: fever\n"
    got = [(r["label"], r["body"]) for r in one(spark, text, C.sections)]
    assert got == [("", "Admitted from home."), ("Chief Complaint", "pain\nno Allergies: here"), ("Allergies", ""), ("Vitals", "T 98.6"), ("Chief Complaint", "fever")]
    assert [tuple(r) for r in one(spark, None, C.sections)] == [("", "")]
    long = "Chief Complaint: " + "word " * 200_000
    assert len(one(spark, long, C.sections)[0]["body"]) == len("word ") * 200_000 - 1


@pytest.mark.parametrize("text, want", [
    ("Seen by Dr. ___ today.", "Seen by Dr. Adler today."),
    ("___ was told, 2.5 mg. Better.", "Better."),
    ("Seen at ___. ___ left; calm.", "Seen. calm."),
    ("No masks. None.", "No masks. None."),
])
def test_unmask(spark, text, want):
    assert one(spark, text, lambda x: C.unmask(x, F.lit(0))) == want


def test_dates_keep_intervals_and_window(spark):
    days = [("a", "2150-03-01"), ("a", "2152-02-29"), ("b", "2110-01-01"), ("b", "2119-01-01"), ("c", "2199-12-31")]
    visits = spark.createDataFrame([(i, {"a": 1, "b": 2, "c": 3}[s], dt.date.fromisoformat(d)) for i, (s, d) in enumerate(days)], "case_id long, subject_id long, recorded_at date")
    got = {r["case_id"]: r for r in C.shifted(visits).collect()}
    assert (got[1]["visited"] - got[0]["visited"]).days == 730 and (got[3]["visited"] - got[2]["visited"]).days == 3287
    assert all(dt.date(2020, 1, 1) <= r["visited"] for r in got.values()) and [got[i]["inside"] for i in range(5)] == [True, True, True, False, True]
    assert one(spark, "on 2150-03-01, not 2150-02-30 or 12150-03-011.", lambda x: C.shift_text(x, F.lit(1))) == "on 2150-03-02, not 2150-02-30 or 12150-03-011."
    assert C.shifted(visits.limit(0)).count() == 0


def test_tables(spark):
    assert one(spark, "Na-140 Foo-3\nfirst Na-140", C.expand_labs) == "Sodium: 140 mmol/L (reference 135-145)\nFoo-3\nfirst Na-140"
    assert one(spark, "hydrOXYzine 10 mg PO QHS PRN itch", C.expand_meds) == "hydroxyzine 10 mg by mouth at bedtime as needed itch"
    assert one(spark, "BP 120/80 HR: 72 tired", C.vitals) == "Heart rate 72 per minute. Blood pressure 120/80 mmHg. tired"
    assert one(spark, "FINDINGS: x\n\nIMPRESSION: clear\nlungs ", C.impression) == "clear\nlungs" and one(spark, "no end", C.impression) == "no end"


def test_normalize_and_harmonize(spark):
    visits = spark.createDataFrame([(1, 7, dt.date(2150, 1, 1), 40, "F", "WARD"), (2, 7, dt.date(2150, 2, 1), 40, "F", "WARD")], "case_id long, subject_id long, recorded_at date, age_years long, sex string, setting string")
    notes = spark.createDataFrame([(1, "Social History: ___ smokes. Chief Complaint\nChief Complaint: pain"), (2, None)], "case_id long, text string")
    reports = spark.createDataFrame([(1, 2, "IMPRESSION: b"), (1, 1, "IMPRESSION: a"), (1, 3, None)], "case_id long, report_id long, text string")
    real = C.normalize(notes, visits, reports)
    got = {(r["case_id"], r["stype"]): r["body"] for r in real.collect()}
    assert got == {(1, "demographics"): "40-year-old woman, ward.", (2, "demographics"): "40-year-old woman, ward.", (1, "chief_complaint"): "pain", (1, "social_history"): "Chief Complaint", (1, "imaging"): "a\nb"}
    own = real.where("stype <> 'demographics'").withColumn("case_id", F.col("case_id") + 10)
    both = C.harmonize(real, own, budget=3)
    assert both.select("stype").distinct().count() == 3 and {r["case_id"] for r in both.collect()} == {1, 11}
    assert C.harmonize(real.limit(0), own).count() == 0
