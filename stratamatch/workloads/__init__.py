"""The experiment workloads as named queries, each with its SQL where SQL can express it."""

from __future__ import annotations

QUERIES: dict = {}
SQL: dict = {}


def query(sql: str | None = None):
    """Register a function (spark, folder) -> DataFrame under its name."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def load() -> None:
    from . import effects, matching, neighbours, preparation, surface, treatments  # noqa: F401
