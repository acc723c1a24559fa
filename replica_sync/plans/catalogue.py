"""All queries of the engine, with the SQL that an independent engine can check them by."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from replica_sync.operators import relational
from replica_sync.plans import engine
from replica_sync.plans.engine import flagship
from replica_sync.streaming import queries as streams

__all__ = ["flagship", "oracle_sql", "queries"]


def _all() -> dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]]:
    return {**engine.QUERIES, **relational.QUERIES, **streams.QUERIES}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, (f, _) in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _all().items() if sql}
