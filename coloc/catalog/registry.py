"""Name -> (query, SQL twin)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is there twice")
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def r4(column: str, name: str | None = None, digits: int = 4) -> Column:
    return (F.round(F.col(column).cast("double"), digits) + F.lit(0.0)).alias(name or column)  # no negative zero


def q4(column: str, name: str | None = None, digits: int = 4) -> str:
    return f"(round(({column})::DOUBLE, {digits}) + 0.0) AS {name or column}"
