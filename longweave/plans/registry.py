"""Queries by name, with the SQL that a reference engine can run on the same tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def everything() -> None:
    """Import all modules that register queries."""
    from longweave.plans import baseline_queries, lm_queries, method_queries, operator_queries, qa_queries, workload_queries  # noqa: F401
    from longweave.streaming import queries  # noqa: F401
