"""The query catalogue: callables on (spark, sf_dir) and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None):
    """Registers a function under its name, with its SQL twin if there is one."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE[f.__name__] = sql
        return f

    return add


def load() -> tuple[dict[str, Callable], dict[str, str]]:
    from . import drift, experiments, relational

    del drift, experiments, relational
    return QUERIES, ORACLE
