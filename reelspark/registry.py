"""Where modules register their queries, with SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        if name in QUERIES:
            raise KeyError(name)
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def load() -> None:
    """Imports every module that registers queries."""
    import importlib

    for m in ("operators.relational", "operators.joins", "operators.windows", "functions.scalar", "functions.udfs", "streaming.queries", "sources.io", "workloads.lifting", "workloads.rendering", "workloads.delivery", "workloads.access", "workloads.search", "workloads.filters", "workloads.studies", "workloads.measures"):
        importlib.import_module(f"reelspark.{m}")
