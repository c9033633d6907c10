"""The registry of queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"two queries named {name}")
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def query(name: str, sql: str | None = None):
    """Registers the decorated function of (spark, sf_dir)."""
    def keep(f):
        add(name, f, sql)
        return f

    return keep
