"""Registered queries with their SQL, by group."""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


class Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.sql: dict[str, str] = {}

    def add(self, key: str, run: Query, sql: str | None = None) -> None:
        if key in self.queries:
            raise ValueError(f"{key} is registered twice")
        self.queries[key] = run
        if sql:
            self.sql[key] = re.sub(r"\bat\b", '"at"', sql)  # a reserved word in DuckDB
