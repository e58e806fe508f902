"""One entry per query key: builder and, where SQL can express it, the DuckDB text."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

FLAGSHIP = "adaptive_rho4"

Builder = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Builder] = {}
_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Builder], Builder]:
    """Register a builder under a key, with its oracle if there is one."""

    def add(build: Builder) -> Builder:
        if name in _QUERIES:
            raise ValueError(f"query {name} is registered twice")
        _QUERIES[name] = build
        if sql:
            _SQL[name] = sql
        return build

    return add


def implement(name: str) -> Callable[[Builder], Builder]:
    """Put the library's own code behind a key whose text then is an oracle only."""

    def replace(build: Builder) -> Builder:
        if name not in _SQL:
            raise ValueError(f"query {name} has no oracle to be held against")
        _QUERIES[name] = build
        return build

    return replace


def _load() -> None:
    """Import the modules that register queries."""
    for name in ("stages", "native", "papertables", "relational", "workloads", "studies"):
        import_module(f"tokenfold.plans.{name}")
    import_module("tokenfold.streaming.streams")


def queries() -> dict[str, Builder]:
    _load()
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    _load()
    return dict(_SQL)
