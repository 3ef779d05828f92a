"""Registry of the engine's own queries and their DuckDB statements."""

from __future__ import annotations

from importlib import import_module

MODULES: tuple[str, ...] = ("methods", "verified", "relational", "experiments", "surfaces")


def collected() -> tuple[dict, dict]:
    """(queries, oracles) of all modules; a name may be given once."""
    queries: dict = {}
    oracles: dict = {}
    for name in MODULES:
        module = import_module(f"evenpart.queries.{name}")
        if twice := queries.keys() & module.QUERIES.keys():
            raise ValueError(f"registered twice: {sorted(twice)}")
        queries |= module.QUERIES
        oracles |= module.ORACLES
    return queries, oracles
