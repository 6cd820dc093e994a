"""Query registry: each key holds the Spark query and, where SQL can state it, the same result as SQL text."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]

_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}
_MODULES: list[str] = ["gridmin.methods", "gridmin.sqlops", "gridmin.stream"]


def register(key: str, sql: str | None = None) -> Callable[[Query], Query]:
    """Decorator that files a query under ``key`` together with its SQL counterpart."""

    def file(fn: Query) -> Query:
        if key in _QUERIES:
            raise ValueError(f"query {key!r} is registered twice")
        _QUERIES[key] = fn
        if sql is not None:
            _ORACLES[key] = sql
        return fn

    return file


def _load() -> None:
    for name in _MODULES:
        importlib.import_module(name)


def queries() -> dict[str, Query]:
    _load()
    return dict(_QUERIES)


def oracles() -> dict[str, str]:
    _load()
    return dict(_ORACLES)
