"""Where queries and the SQL that states their results are registered."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
FOUND: dict[str, tuple[Query, str | None]] = {}


def add(name: str, run: Query, sql: str | None = None) -> None:
    if name in FOUND:
        raise ValueError(f"{name} is registered twice")
    FOUND[name] = (run, sql)
