"""Typed arguments, roles, the patient's scope and submitted answers."""

import pytest

from caseloom.functions import tools as T
from caseloom.sources.tables import Tables

SF = "/root/testdata/sf0.001"


def test_registry_and_types(spark):
    t = Tables(spark, SF)
    assert len(T.REGISTRY) == 13 and all(x.arguments["patient_id"] == "bigint" for x in T.REGISTRY.values())
    one = spark.createDataFrame([(1, 42)], "call_id long, patient_id long")
    with pytest.raises(ValueError, match="no tool"):
        T.call(t, "drop_table", one)
    with pytest.raises(ValueError, match="words as string, not None"):
        T.call(t, "search_notes", one)
    with pytest.raises(ValueError, match="patient_id as bigint, not string"):
        T.call(t, "get_profile", one.selectExpr("call_id", "cast(patient_id as string) AS patient_id"))
    roles = {"clinician": {"Observation"}}
    assert T.allowed(roles, "clinician", "get_labs") and T.allowed(roles, "nobody", "submit_answer") and not T.allowed(roles, "billing", "get_labs") and not T.allowed(roles, "clinician", "find_patient")


def test_scope(spark):
    """Another patient's encounter, unknown patients, nulls and repeated calls."""
    t = Tables(spark, SF)
    first = {r["o_custkey"]: r["k"] for r in t.orders.groupBy("o_custkey").agg({"o_orderkey": "min"}).withColumnRenamed("min(o_orderkey)", "k").collect()}
    (p, own), (_, other) = list(first.items())[:2]
    calls = spark.createDataFrame([(1, p, own), (2, p, other), (3, -1, own), (4, None, own), (5, p, None), (6, p, own)], "call_id long, patient_id long, encounter_id long")
    assert sorted(r["call_id"] for r in T.call(t, "get_encounter", calls).collect()) == [1, 6]
    assert {r["call_id"] for r in T.call(t, "list_sections", calls).collect()} == {1, 6}
    assert T.call(t, "get_encounter", calls.limit(0)).count() == 0


def test_submitted(spark):
    t = Tables(spark, SF)
    rows = [(2, 7, "diagnosis", [9]), (1, 7, "diagnosis", [3, 3, 4]), (3, 7, "poetry", [1]), (4, -7, "imaging", [1]), (5, 7, "imaging", []), (6, 7, "retrieval", None)]
    calls = spark.createDataFrame(rows, "call_id long, patient_id long, task string, items array<long>")
    assert sorted(tuple(r) for r in T.call(t, "submit_answer", calls).collect()) == [(1, 7, "diagnosis", 3), (1, 7, "diagnosis", 4)]
