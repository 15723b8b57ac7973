"""Registered queries: every tool called for all users of the call log, whose first encounter is the one asked for."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import tools as T
from ..plans.oracle import VIEWS, sql
from ..sources.tables import Tables
from .registry import register

VIEWS["tool_call"] = "SELECT user_id AS call_id, subject_id, min(case_id) AS encounter_id FROM (SELECT DISTINCT user_id FROM events) JOIN src_case ON subject_id = user_id GROUP BY 1, 2"
VIEWS["tool_case"] = "SELECT * FROM tool_call JOIN src_case USING (subject_id)"


def calls(t):
    users = t.events.select(F.col("user_id").alias("patient_id")).distinct()
    first = t.orders.groupBy(F.col("o_custkey").alias("patient_id")).agg(F.min("o_orderkey").alias("encounter_id"))
    rows = users.join(first, "patient_id").select(F.col("patient_id").alias("call_id"), "patient_id", "encounter_id")
    own = [F.when(F.col("patient_id") % 2 == 0, a).otherwise(b) for a, b in (("lab", "imaging"), ("diagnosis", "guess"))]
    return rows.withColumns({"section": own[0], "words": F.lit("ANVIL"), "task": own[1], "items": F.array("encounter_id", "encounter_id", "patient_id")})


def finding(kind):
    return f"SELECT DISTINCT call_id, case_id, term FROM tool_case JOIN case_finding USING (case_id) JOIN finding_node USING (finding_id) WHERE kind = '{kind}'"


TWINS = {
    "find_patient": "SELECT call_id, c_name AS name FROM tool_call JOIN customer ON c_custkey = subject_id",
    "get_profile": "SELECT call_id, count(*) AS encounters, max(sex) AS sex FROM tool_case GROUP BY 1",
    "list_encounters": "SELECT call_id, case_id, acuity FROM tool_case",
    "get_encounter": "SELECT call_id, case_id, setting, acuity FROM tool_case WHERE case_id = encounter_id",
    "list_sections": "SELECT call_id, section_id, stype FROM tool_call JOIN chart_section ON case_id = encounter_id",
    "get_section": "SELECT call_id, section_id, body FROM tool_call JOIN chart_section ON case_id = encounter_id AND stype = CASE subject_id % 2 WHEN 0 THEN 'lab' ELSE 'imaging' END",
    "search_notes": "SELECT call_id, section_id FROM tool_case JOIN chart_section USING (case_id) WHERE contains(body, 'anvil')",
    "list_problems": "SELECT DISTINCT call_id, dx_id FROM tool_case JOIN case_dx USING (case_id)",
    "list_medications": finding("medication"),
    "list_findings": "SELECT call_id, case_id, finding_id, relevance FROM tool_case JOIN case_finding USING (case_id)",
    "get_labs": finding("lab"),
    "list_imaging": finding("imaging"),
    "submit_answer": "SELECT DISTINCT call_id, subject_id AS patient_id, 'diagnosis' AS task, unnest([encounter_id, subject_id]) AS item_id FROM tool_call WHERE subject_id % 2 = 0",
}


def answers(name):
    def run(spark, sf_dir):
        t = Tables(spark, sf_dir)
        return T.call(t, name, calls(t))

    return run


for name, text in TWINS.items():
    register(f"q_tool_{name}", answers(name), sql(text))


def described(spark, sf_dir):
    """Every argument of every tool, and in how many calls of the log it is given."""
    log = calls(Tables(spark, sf_dir))
    given = log.agg(*[F.count(c).alias(c) for c in log.columns]).unpivot([], log.columns, "argument", "calls")
    return spark.createDataFrame(T.described(), "tool string, place int, argument string, type string").join(given, "argument").select("tool", "place", "argument", "type", "calls")


GIVEN = "(SELECT count(*) AS calls FROM (SELECT DISTINCT user_id FROM events) JOIN (SELECT DISTINCT o_custkey FROM orders) ON user_id = o_custkey)"
register("q_tool_registry", described, f"SELECT tool, CAST(place AS INT) AS place, argument, type, calls FROM (VALUES {', '.join(map(str, T.described()))}) AS d(tool, place, argument, type), {GIVEN}")
