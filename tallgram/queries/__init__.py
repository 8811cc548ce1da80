"""Registered queries of the library and, where SQL can say the same, their DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    if name in _QUERIES:
        raise ValueError(f"{name} is registered twice")
    _QUERIES[name] = query
    if sql is not None:
        _ORACLES[name] = sql


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def registered(f: Query) -> Query:
        add(name, f, sql)
        return f

    return registered


def all_queries() -> tuple[dict[str, Query], dict[str, str]]:
    from tallgram.queries import core, relational, streams  # noqa: F401  they register themselves

    return dict(_QUERIES), dict(_ORACLES)
