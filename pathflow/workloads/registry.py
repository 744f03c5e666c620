"""Registry of queries and their reference SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .graphs import Graphs

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    """Register fn(graphs) under its name, with SQL for the same rows where SQL can say it."""

    def add(fn: Callable[[Graphs], DataFrame]):
        key = name or fn.__name__
        QUERIES[key] = lambda spark, sf_dir: fn(Graphs(spark, sf_dir))
        if sql:
            ORACLES[key] = sql
        return fn

    return add
