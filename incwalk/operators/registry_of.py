"""A registry that a module fills by decorating its queries."""

from __future__ import annotations

from collections.abc import Callable


class Registry:
    def __init__(self):
        self.queries: dict[str, Callable] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, fn: Callable, sql: str | None = None) -> None:
        self.queries[name] = fn
        if sql is not None:
            self.sql[name] = sql

    def query(self, sql: str | None = None, name: str | None = None):
        def wrap(fn):
            self.add(name or fn.__name__, fn, sql)
            return fn

        return wrap
