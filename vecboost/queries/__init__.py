"""Registered queries and, beside each, independent SQL for the same rows."""

from __future__ import annotations

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    """Registers a function (spark, sf_dir) under its name, with its SQL if it has one."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def load_all() -> None:
    from . import boosters, experiments, extras, measures, relational, steps  # noqa: F401
