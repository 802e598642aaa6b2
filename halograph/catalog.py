"""All queries of the engine by name, each with the SQL that gives the same rows.

A query is entered by ``query(name, sql)``; sections of the survey are modules that do so when imported.
"""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def enter(f: Callable) -> Callable:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return enter


from halograph import queries as _queries  # noqa: E402,F401  enters all sections
