"""Queries over the given tables: each method, measure and operator, with its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Register a query (spark, sf_dir) under its name, with the SQL that gives the same rows."""

    def put(f: Callable) -> Callable:
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return put


def load_all() -> None:
    from . import graphs, methods, operators, streams, workloads  # noqa: F401
