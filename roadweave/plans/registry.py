"""Named queries with, where SQL can express them, their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Run = Callable[[SparkSession, str], DataFrame]


class Catalog:
    """Queries of one module."""

    def __init__(self) -> None:
        self.queries: dict[str, Run] = {}
        self.sql: dict[str, str] = {}

    def add(self, sql: str | None = None, *, name: str | None = None) -> Callable[[Run], Run]:
        """Register a function as a query under its own name."""

        def keep(run: Run) -> Run:
            key = name or run.__name__
            if key in self.queries:
                raise ValueError(f"query {key} is there already")
            self.queries[key] = run
            if sql is not None:
                self.sql[key] = sql
            return run

        return keep
