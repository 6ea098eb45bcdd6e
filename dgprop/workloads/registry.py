"""Queries by name, with their SQL for DuckDB where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None) -> Callable[[Query], Query]:
    """Register a function under its name."""

    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def r(column: Column | str, places: int = 6) -> Column:
    """Rounded, and never the negative zero."""
    return F.round(F.col(column) if isinstance(column, str) else column, places) + F.lit(0.0)


def sql_r(text: str, places: int = 6) -> str:
    return f"(round({text}, {places}) + 0.0)"


def long_form(df: DataFrame, *keys: str, array: str = "z", places: int = 6) -> DataFrame:
    """One row for each place of an array."""
    return df.select(*keys, F.posexplode(array).alias("dim", "v")).select(*keys, "dim", r("v", places).alias("z"))
