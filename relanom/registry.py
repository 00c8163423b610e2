"""Queries by name, each with the SQL that must give the same rows where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    """Register a function (spark, sf_dir) -> DataFrame, with its oracle if there is one."""

    def add(function: Query) -> Query:
        if name in _queries:
            raise ValueError(f"two queries are named {name}")
        _queries[name] = function
        if oracle:
            _oracles[name] = oracle
        return function

    return add


def queries() -> dict[str, Query]:
    import relanom.queries  # noqa: F401  registers on import

    return _queries


def oracles() -> dict[str, str]:
    queries()
    return _oracles


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return queries()["flagship_cyber"](spark, sf_dir)
