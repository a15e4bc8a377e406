"""Registered queries and their independent DuckDB oracles, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .plans import methods, oracles as sql, relational, workloads

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {f.__name__: f for f in [*methods.QUERIES, *workloads.QUERIES, *relational.QUERIES]}


def oracles() -> dict[str, str]:
    return sql.oracles()
