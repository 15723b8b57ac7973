"""The function-calling interface over the served records: 13 tools with typed arguments.

A tool answers a frame of calls at once, (call_id, its arguments); every answer row carries its call_id.  So a million agents' calls are one join, and the
answers to one call are those of a frame with one row.  Nothing outside the call's patient is ever in an answer.  The names are ours [D].
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import Tables

#: The tasks that take answers.
TASKS = ("diagnosis", "summarization", "retrieval", "imaging")


@dataclass(frozen=True)
class Tool:
    name: str
    arguments: dict[str, str]
    answer: Callable[[Tables, DataFrame], DataFrame]
    #: The kind of resource that a role has to be allowed to read; None for a tool that writes.
    resource: str | None


REGISTRY: dict[str, Tool] = {}


def tool(resource: str | None, **arguments: str):
    def add(fn):
        name = fn.__name__.rstrip("_")
        REGISTRY[name] = Tool(name, {"patient_id": "bigint"} | arguments, fn, resource)
        return fn

    return add


def call(t: Tables, name: str, calls: DataFrame) -> DataFrame:
    """Answers to calls of one tool.  Unknown tools, missing arguments and wrong types raise ValueError before anything runs."""
    if name not in REGISTRY:
        raise ValueError(f"no tool named {name}")
    got = {f.name: f.dataType.simpleString() for f in calls.schema.fields}
    for arg, kind in ({"call_id": "bigint"} | REGISTRY[name].arguments).items():
        if got.get(arg) != kind:
            raise ValueError(f"{name} takes {arg} as {kind}, not {got.get(arg)}")
    return REGISTRY[name].answer(t, calls.select("call_id", *REGISTRY[name].arguments))


def allowed(roles: dict[str, set[str]], role: str, name: str) -> bool:
    """Whether a role may call a tool; everyone may submit an answer."""
    need = REGISTRY[name].resource
    return need is None or need in roles.get(role, set())


def described() -> list[tuple[str, int, str, str]]:
    """(tool, place, argument, type) of all tools."""
    return [(x.name, i, a, k) for x in REGISTRY.values() for i, (a, k) in enumerate(x.arguments.items())]


def cases(t: Tables, calls: DataFrame) -> DataFrame:
    return calls.join(t.src_case, F.col("patient_id") == F.col("subject_id"))


def findings(t: Tables, calls: DataFrame, kind: str) -> DataFrame:
    node = t.finding_node.where(F.col("kind") == kind).select("finding_id", "term")
    return cases(t, calls).select("call_id", "case_id").join(t.case_finding.select("case_id", "finding_id"), "case_id").join(node, "finding_id").select("call_id", "case_id", "term").distinct()


@tool("Patient")
def find_patient(t, calls):
    return calls.join(t.customer, F.col("patient_id") == F.col("c_custkey")).select("call_id", F.col("c_name").alias("name"))


@tool("Patient")
def get_profile(t, calls):
    return cases(t, calls).groupBy("call_id").agg(F.count("*").alias("encounters"), F.max("sex").alias("sex"))


@tool("Encounter")
def list_encounters(t, calls):
    return cases(t, calls).select("call_id", "case_id", "acuity")


@tool("Encounter", encounter_id="bigint")
def get_encounter(t, calls):
    return cases(t, calls).where("case_id = encounter_id").select("call_id", "case_id", "setting", "acuity")


@tool("DocumentReference", encounter_id="bigint")
def list_sections(t, calls):
    return cases(t, calls).where("case_id = encounter_id").select("call_id", "case_id").join(t.chart_section, "case_id").select("call_id", "section_id", "stype")


@tool("DocumentReference", encounter_id="bigint", section="string")
def get_section(t, calls):
    return cases(t, calls).where("case_id = encounter_id").select("call_id", "case_id", "section").join(t.chart_section, "case_id").where("stype = section").select("call_id", "section_id", "body")


@tool("DocumentReference", words="string")
def search_notes(t, calls):
    """Sections of the patient's notes that hold the words, in any letters."""
    return cases(t, calls).select("call_id", "case_id", "words").join(t.chart_section, "case_id").where(F.contains(F.lower("body"), F.lower("words"))).select("call_id", "section_id")


@tool("Condition")
def list_problems(t, calls):
    return cases(t, calls).select("call_id", "case_id").join(t.case_dx.select("case_id", "dx_id"), "case_id").select("call_id", "dx_id").distinct()


@tool("MedicationStatement")
def list_medications(t, calls):
    return findings(t, calls, "medication")


@tool("Observation")
def list_findings(t, calls):
    return cases(t, calls).select("call_id", "case_id").join(t.case_finding, "case_id").select("call_id", "case_id", "finding_id", "relevance")


@tool("Observation")
def get_labs(t, calls):
    return findings(t, calls, "lab")


@tool("ImagingStudy")
def list_imaging(t, calls):
    return findings(t, calls, "imaging")


@tool(None, task="string", items="array<bigint>")
def submit_answer(t, calls):
    """One row per submitted item, once; calls for an unknown task or patient have none.  Of several answers to a task and patient the first call counts."""
    known = calls.where(F.col("task").isin(*TASKS)).join(t.customer.select(F.col("c_custkey").alias("patient_id")), "patient_id", "left_semi")
    first = known.groupBy("patient_id", "task").agg(F.min_by("items", "call_id").alias("items"), F.min("call_id").alias("call_id"))
    return first.select("call_id", "patient_id", "task", F.explode(F.array_distinct("items")).alias("item_id"))
