"""Registered queries, one for each method, measure, workload or operator, with DuckDB SQL of what SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | Callable[[], str] | None = None):
    """Register a query under its function's name."""

    def add(f):
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle() if callable(oracle) else oracle
        return f

    return add


def load() -> tuple[dict, dict]:
    from xlsql.queries import construction, evaluation, statistics, surface  # noqa: F401

    return QUERIES, ORACLES


def quote(x) -> str:
    """SQL literal."""
    if x is None:
        return "NULL"
    return "'" + x.replace("'", "''") + "'" if isinstance(x, str) else f"CAST({x!r} AS DOUBLE)" if isinstance(x, float) else str(x)


def values(rows, columns: str, name: str = "v") -> str:
    """(VALUES ...) name(columns)"""
    return "(VALUES " + ", ".join("(" + ", ".join(quote(x) for x in r) + ")" for r in rows) + f") {name}({columns})"
