"""The table of registered queries: each name with its function and, where SQL can state it, its oracle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


class EntryTable:
    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.oracles: dict[str, str] = {}

    def add(self, name: str, fn: Query, sql: str | None = None) -> None:
        if name in self.queries:
            raise ValueError(f"query {name!r} is registered twice")
        self.queries[name] = fn
        if sql is not None:
            self.oracles[name] = sql

    def query(self, sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
        """Decorator: register a function under its own name."""

        def put(fn: Query) -> Query:
            self.add(name or fn.__name__, fn, sql)
            return fn

        return put
