"""Collects (key, DataFrame function, DuckDB SQL) of the library's own queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(key: str, sql: str | None = None):
    """Registers the decorated (spark, sf_dir) function under key, with its SQL twin if given."""

    def put(f):
        if key in _QUERIES:
            raise ValueError(f"two queries named {key}")
        _QUERIES[key] = f
        if sql is not None:
            _SQL[key] = sql
        return f

    return put


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return _QUERIES


def oracle_sql() -> dict[str, str]:
    return _SQL


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _QUERIES["pipeline_end_to_end"](spark, sf_dir)


def load() -> None:
    """Imports the modules that register queries."""
    import kgtrail.queries  # noqa: F401
