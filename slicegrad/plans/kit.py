"""Registration of queries with their SQL."""

from __future__ import annotations


class Book:
    def __init__(self):
        self.queries: dict = {}
        self.oracles: dict[str, str] = {}

    def add(self, key: str, sql: str | None = None):
        def keep(f):
            self.queries[key] = f
            if sql is not None:
                self.oracles[key] = sql
            return f

        return keep
