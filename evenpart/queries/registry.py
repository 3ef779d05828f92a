"""The decorator by which a module lists its queries and their DuckDB statements."""

from __future__ import annotations

from collections.abc import Callable


def registry() -> tuple[dict, dict, Callable]:
    """(queries, oracles, decorator): ``@query(sql)`` registers a function under its name, or under ``name``."""
    queries: dict = {}
    oracles: dict = {}

    def query(sql: str | None = None, name: str | None = None):
        def add(f):
            queries[name or f.__name__] = f
            if sql:
                oracles[name or f.__name__] = sql
            return f

        return add

    return queries, oracles, query
