"""All queries of the library and the SQL that says the same, gathered from the modules that define them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from writelite.workloads import measures, models, relational, sorting, streams

Query = Callable[[SparkSession, str], DataFrame]
MODULES: tuple = (sorting, models, measures, relational, streams)


def queries() -> dict[str, Query]:
    return {name: q for m in MODULES for name, q in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in MODULES for name, sql in m.SQL.items()}
