"""Queries register themselves here, with the DuckDB text that gives the same rows."""

from __future__ import annotations

from catalogflow.session import table as load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        if key in QUERIES:
            raise ValueError(f"{key} is registered twice")
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


__all__ = ["ORACLES", "QUERIES", "load", "query"]
