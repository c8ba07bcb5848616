from __future__ import annotations

from collections.abc import Callable

from ..sources.tables import tidy


class Registry:
    def __init__(self):
        self.queries: dict[str, Callable] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, sql: str | None = None):
        """Decorator: register fn(spark, sf_dir) under name with the SQL that gives the same rows."""

        def put(fn):
            self.queries[name] = tidy(fn)
            if sql is not None:
                self.sql[name] = sql
            return fn

        return put
