"""Named workloads: each a Spark query over a folder of tables, most with SQL that says the same by definition."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Register a workload under its function's name."""
    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return add


def register_all() -> None:
    from linkblock.plans import blocking, operators, sketches, texts  # noqa: F401
    from linkblock.streaming import workloads  # noqa: F401
