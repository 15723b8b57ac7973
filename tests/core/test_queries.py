"""A spread of registered queries against DuckDB on the smallest tables, and plan shapes."""

import duckdb
import pytest

import __spark_entry__ as entry
from caseloom.operators import registry
from caseloom.sources.tables import NAMES

SF = "/root/testdata/sf0.001"
KEYS = ["q_sev_f1_neutral", "q_finding_f1", "q_p_at_5", "q_mean_rank", "q_ground_cascade", "q_dx_links", "q_split_assign", "q_problem_carry", "q_jsd", "q_fleiss", "q_asof", "q_range_join", "q_session", "q_bm25", "q_cluster_invariants", "q_agent_effects", "q_rel_recall", "q_split_balance", "q_provenance_gaps", "q_convert_all", "q_convert_sections", "q_harmonize_sections", "q_shift_dates"]


def rows(df):
    show = lambda v: "NULL" if v is None or v != v else f"{v:.6f}" if isinstance(v, float) else str(v)[:19]
    return sorted(tuple(show(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("key", KEYS)
def test_same_as_duckdb(spark, key):
    con = duckdb.connect()
    for n in NAMES:
        con.sql(f"CREATE VIEW {n} AS SELECT * FROM read_parquet('{SF}/{n}.parquet')")
    got, want = registry.queries()[key](spark, SF).toPandas(), con.sql(registry.oracle_sql()[key]).df()
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() == 10
    assert set(registry.oracle_sql()) <= set(registry.queries())


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    q = registry.queries()
    assert "PushedFilters: [IsNotNull(o_orderdate)" in plan(q["q_scan_cases"](spark, SF))
    assert "WindowGroupLimit" in plan(q["q_topk_group"](spark, SF))
    for key in ("q_link_shared", "q_range_join", "q_problem_carry", "q_case_edges"):
        assert "CartesianProduct" not in plan(q[key](spark, SF)) and "BroadcastNestedLoopJoin" not in plan(q[key](spark, SF))


def test_split_strata_match(spark):
    """Training and held-out patients match within two places of a stratum, and no patient is in two splits."""
    from caseloom.functions import splits
    from caseloom.sources.tables import Tables

    got = splits.assign(Tables(spark, "/root/testdata/sf0.01")).toPandas()
    assert got["patient_id"].is_unique and set(got["split"]) == {"public", "heldout", "training"}
    n = got["split"].value_counts()
    assert abs(n["public"] / len(got) - 200 / 1268) < 1 / len(got) and abs(n["heldout"] / len(got) - 268 / 1268) < 2 / len(got)
    rest = got[got["split"] != "public"]
    share = rest.groupby(["chapter", "band"])["split"].value_counts(normalize=False).unstack(fill_value=0)
    assert ((share["training"] / n["training"] - share["heldout"] / n["heldout"]).abs() <= 0.01).all()


def test_silent_systems_and_instances_score_zero(spark):
    from pyspark.sql import functions as F

    from caseloom.functions import score as S

    gold = spark.createDataFrame([(1, 10, 2), (1, 11, 1), (2, 10, 3)], "patient_id long, dx_id long, weight int")
    pred = spark.createDataFrame([(1, 1, 10), (1, 1, 99)], "m int, patient_id long, dx_id long")
    systems = spark.createDataFrame([(1,), (2,)], "m int")
    got = {(r["m"], r["patient_id"]): round(r["value"], 6) for r in S.severity_f1(pred, gold, systems=systems).collect()}
    assert got == {(1, 1): round(2 * 2 / (3 + 3), 6), (1, 2): 0.0, (2, 1): 0.0, (2, 2): 0.0}
    grades = spark.createDataFrame([(1, 5, 3), (2, 6, 3)], "patient_id long, section_id long, grade int")
    ranked = spark.createDataFrame([(1, 1, 5, 1)], "m int, patient_id long, section_id long, rank long")
    for f, one in ((S.precision_at, 0.2), (S.ndcg_at, 1.0)):
        assert {(r["m"], r["patient_id"]): r["value"] for r in f(ranked, grades, systems=systems).select("m", "patient_id", F.round("value", 6).alias("value")).collect()} == {(1, 1): one, (1, 2): 0.0, (2, 1): 0.0, (2, 2): 0.0}
