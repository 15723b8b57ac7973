"""The query registry: every public method registers a Spark query and, where SQL can say it, its DuckDB twin."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}
#: Modules that register queries when imported.
MODULES = ["caseloom.operators.scoring", "caseloom.operators.construct", "caseloom.operators.surface", "caseloom.operators.realism", "caseloom.operators.conversion", "caseloom.operators.serving", "caseloom.operators.io"]


def register(key: str, fn: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    if key in _QUERIES:
        raise ValueError(f"query {key} is registered twice")
    _QUERIES[key] = fn
    if sql:
        _SQL[key] = sql


def _load() -> None:
    for m in MODULES:
        importlib.import_module(m)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    _load()
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    _load()
    return dict(_SQL)
