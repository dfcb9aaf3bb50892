"""Driver queries of the engine, by name, with their DuckDB twins where SQL can state the result.

Results are rounded to six decimals, and zero is added, so that both engines print the same numbers.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def rounded(column, digits: int = 6):
    return F.round(F.col(column) if isinstance(column, str) else column, digits) + F.lit(0.0)


from .workloads import distribution, published, solves, streams, surrounding, transforms  # noqa: E402, F401
