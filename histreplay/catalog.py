"""All queries of the engine by name, and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from histreplay.queries import measures, methods, streams, surface, workloads

CATALOGS = (methods.QUERIES, workloads.QUERIES, measures.QUERIES, surface.QUERIES, streams.QUERIES)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: run for c in CATALOGS for name, (run, _) in c.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for c in CATALOGS for name, (_, sql) in c.items() if sql}
