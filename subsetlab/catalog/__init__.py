"""Queries with their SQL side by side; each module fills a Registry."""

from __future__ import annotations

from . import compare, core, relational, stream, workload

MODULES = (core, compare, workload, relational, stream)


def queries() -> dict:
    return {name: fn for m in MODULES for name, fn in m.R.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in MODULES for name, sql in m.R.sql.items()}
