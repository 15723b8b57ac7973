"""Worked examples and published tables."""

import math

import pytest
from pyspark.sql import functions as F

from caseloom import fixtures
from caseloom.functions import patients
from caseloom.functions import score as S
from caseloom.functions import stats as X


def test_instance_counts():
    assert [sum(v[k] for v in fixtures.INSTANCE_COUNTS.values()) for k in range(3)] == [1859, 2536, 7619]


def test_published_mean_ranks(spark):
    got = {r["m"]: r["mean_rank"] for r in S.mean_rank(fixtures.panel_scores(spark)).collect()}
    assert got == pytest.approx(fixtures.MEAN_RANKS)


def test_published_agent_effects(spark):
    got = {(r["task"], r["m"]): r for r in S.decompose(fixtures.agent_scores(spark), keys=["task", "m"]).collect()}
    for task, m, *_, loop, retrieval in fixtures.AGENT_SCORES:
        assert got[task, m]["loop_effect"] == pytest.approx(loop, abs=0.0011)
        assert got[task, m]["retrieval_effect"] == pytest.approx(retrieval, abs=0.0011)


def test_severity_example(spark):
    gold = spark.createDataFrame([(1, "A", 2), (1, "B", 2), (1, "C", 3)], "patient_id int, dx_id string, weight int")
    pred = spark.createDataFrame([(1, 1, x) for x in "AACDE"], "m int, patient_id int, dx_id string")
    chart = spark.createDataFrame([(1, x) for x in "ABCD"], "patient_id int, dx_id string")
    value = lambda **k: S.severity_f1(pred, gold, **k).first()["value"]
    assert value(extra=1.5) == pytest.approx(10 / 15)
    assert value(neutral=chart, extra=2.0) == pytest.approx(10 / 14)
    assert value(neutral=chart) >= value()


def test_rank_example(spark):
    grades = spark.createDataFrame([(1, i, g) for i, g in enumerate((3, 2, 1, 0))], "patient_id int, section_id int, grade int")
    ranked = spark.createDataFrame([(0, 1, 0, 1), (0, 1, 3, 2), (0, 1, 1, 3)], "m int, patient_id int, section_id int, rank int")
    assert S.ndcg_at(ranked, grades, k=3).first()["value"] == pytest.approx(0.904950, abs=1e-5)
    assert S.ndcg_at(ranked, grades, k=3, kind="linear").first()["value"] == pytest.approx(0.840008, abs=1e-5)
    assert S.precision_at(ranked, grades).first()["value"] == pytest.approx(0.4)


def test_abstention_and_zero_fill(spark):
    inst = spark.createDataFrame([(1,), (2,)], "p int")
    gold = spark.createDataFrame([(1, 5)], "p int, i int")
    pred = spark.createDataFrame([(0, 1, 5), (0, 1, 5)], "m int, p int, i int")
    got = {r["p"]: r["value"] for r in S.set_prf(pred, gold, keys=["p"], item="i", instances=inst).collect()}
    assert got == {1: 1.0, 2: 1.0}
    some = spark.createDataFrame([(0, 1, 0.5)], "m int, p int, value double")
    assert {r["p"]: r["value"] for r in S.complete(inst, some, some, key="p").collect()} == {1: 0.5, 2: 0.0}


def test_statistics(spark):
    assert X.binom_two_sided(53, 100) == pytest.approx(0.617299, abs=1e-6)
    assert X.binom_two_sided(9, 10) == pytest.approx(0.021484, abs=1e-6)
    assert X.t_two_sided(0.20, 9) == pytest.approx(0.85, abs=0.005)
    p = spark.createDataFrame([(1, 0.01), (2, 0.04), (3, 0.03)], "rater int, p double")
    assert {r["rater"]: round(r["adjusted"], 6) for r in X.holm(p).collect()} == {1: 0.03, 2: 0.06, 3: 0.06}
    calls = spark.createDataFrame([(i, c) for i, n in enumerate((3, 2, 1, 0)) for c in [1] * n + [0] * (3 - n)], "record_id int, called int")
    assert X.fleiss_kappa(calls).first()["kappa"] == pytest.approx(0.333333, abs=1e-6)
    a, b = spark.createDataFrame([("x",), ("y",)], "k string"), spark.createDataFrame([("x",)], "k string")
    assert X.jsd(a, b, "k").first()["jsd"] == pytest.approx(0.311278, abs=1e-6)
    xy = spark.createDataFrame([(1, 10), (2, 30), (2, 20), (4, 40)], "x int, y int")
    assert X.spearman(xy, "x", "y").first()["rho"] == pytest.approx(0.948683, abs=1e-6)
    units = spark.createDataFrame([(i, float(i % 100 < 53)) for i in range(400)], "id long, v double")
    ci = X.bootstrap_ci(units, "v", 300).first()
    assert ci["low"] < 0.53 < ci["high"] and math.isclose(ci["high"] - ci["low"], 0.098, abs_tol=0.03)


def test_example_patient(spark):
    cases = spark.createDataFrame([(1, "M", 52), (2, "M", 58), (3, "M", 58), (4, "F", 55), (5, "M", 64), (6, "M", 53)], "case_id long, sex string, age_years int")
    dx = [(1, 10, "primary"), (2, 10, "secondary"), (2, 11, "primary"), (3, 11, "primary"), (4, 10, "primary"), (5, 10, "primary"), (6, 10, "differential"), (6, 99, "primary")]
    case_dx = spark.createDataFrame(dx, "case_id long, dx_id long, role string")
    for f in (patients.cluster,):
        got = {}
        for r in f(cases, case_dx).collect():
            got.setdefault(r["patient_id"], set()).add(r["case_id"])
        assert {1, 2, 3} in got.values() or {1, 2} in got.values() or {2, 3} in got.values()
        assert all(not ({1, 5} <= g or {4} < g or {6} < g) for g in got.values())
    import pandas as pd

    rows = pd.DataFrame([(c, a, d) for c, a in ((1, 52), (2, 58), (3, 58)) for x, d, r in dx if x == c], columns=["case_id", "age_years", "dx_id"])
    assert patients.grow(rows)["patient_id"].nunique() == 1
