"""All queries of the reference engine, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    """Decorator: adds a query, and its DuckDB twin where there is one."""

    def add(function):
        QUERIES[name] = function
        if sql is not None:
            ORACLE_SQL[name] = sql
        return function

    return add


def load() -> None:
    """Imports the modules whose queries belong here."""
    from basisflow.plans import baselines, counts, deployment, experiments, network, relational, schemes  # noqa: F401
