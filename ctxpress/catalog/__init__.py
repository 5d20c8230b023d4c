"""Named queries over the given tables, each with the same in SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

QUERIES: dict[str, Callable] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Registers a function (spark, sf_dir) under its name, with its SQL."""

    def mark(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLE[name or f.__name__] = sql
        return f

    return mark


def load_all() -> tuple[dict, dict]:
    from ctxpress.catalog import abbreviation, experiments, information, methods, numbers, relational, streams, twins  # noqa: F401

    return QUERIES, ORACLE
