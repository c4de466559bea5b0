"""Where query modules register what they offer."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .context import Tables

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None, tables: type[Tables] = Tables):
    """Registers a function of ``Tables`` under ``name``, with SQL that must give the same rows where SQL can."""

    def add(f: Callable[[Tables], DataFrame]):
        QUERIES[name] = lambda spark, sf_dir: f(tables(spark, sf_dir))
        if sql:
            ORACLES[name] = sql
        return f

    return add
