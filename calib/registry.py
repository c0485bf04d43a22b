"""Queries and their DuckDB equivalents, collected by decorator."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | Callable[[], str] | None = None):
    """Registers a function (spark, sf_dir) -> DataFrame under its name, with SQL that gives the same rows."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql() if callable(sql) else sql
        return f

    return add
