"""The catalogue of queries, each with SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def catalogue() -> tuple[dict[str, Query], dict[str, str]]:
    from patternlm.queries import automata, corpus, events, experiments, models, search  # noqa: F401

    return QUERIES, SQL
