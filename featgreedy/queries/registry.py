"""Names, functions and SQL of the catalogue."""

from __future__ import annotations

from featgreedy.sources.tables import table

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None, name: str | None = None):
    """Register a function of (spark, sf_dir); ``sql`` gives the same rows in DuckDB."""

    def add(fn):
        key = name or fn.__name__
        QUERIES[key] = fn
        if sql:
            ORACLES[key] = sql
        return fn

    return add


t = table
