"""Registry of all queries and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

MODULES = ("grading", "ranking", "profiles", "bank", "statements", "spatial", "relational", "streams")

QUERIES: dict[str, Callable] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a query; ``sql`` is its DuckDB twin."""

    def put(function: Callable) -> Callable:
        QUERIES[name] = function
        if sql:
            SQL[name] = sql
        return function

    return put


def load() -> tuple[dict[str, Callable], dict[str, str]]:
    for name in MODULES:
        import_module(f"{__name__}.{name}")
    return QUERIES, SQL


def rounded(df, *names, digits: int = 6):
    """Doubles rounded for comparison between engines."""
    from pyspark.sql import functions as F

    return df.withColumns({n: F.round(F.col(n).cast("double"), digits) for n in names})
