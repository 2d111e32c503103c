"""Queries over the given tables, by the names of the blueprint, with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    """Registers a query; sql is DuckDB's for the same rows, None where SQL can't say them."""

    def add(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"two queries named {name}")
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


MODULES = ("dedup_queries", "curation", "images_queries", "measures", "relational", "streams_queries")


def load() -> None:
    """Imports the modules that register queries."""
    import importlib

    for name in MODULES:
        importlib.import_module(f"corpusloom.plans.{name}")


load()
