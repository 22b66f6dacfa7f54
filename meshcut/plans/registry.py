"""Queries by name, each with the SQL it is held against where SQL can express it."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        if name in QUERIES:
            raise ValueError(f"query {name} is registered twice")
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def ctes(*parts: tuple[str, str], select: str) -> str:
    return "WITH " + ", ".join(f"{n} AS ({s})" for n, s in parts) + f" {select}"
