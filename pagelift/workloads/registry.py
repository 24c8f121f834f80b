"""Registers queries under a name, with their SQL where there is one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


class Registry:
    def __init__(self):
        self.queries: dict[str, Query] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, query: Query, sql: str | None = None) -> None:
        if name in self.queries:
            raise ValueError(f"two queries are called {name}")
        self.queries[name] = query
        if sql:
            self.sql[name] = sql

    def query(self, name: str, sql: str | None = None):
        def take(f: Query) -> Query:
            self.add(name, f, sql)
            return f

        return take
