"""Queries over the given tables, one key per method, baseline, measure, workload or operator, and their SQL for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_oracles: dict[str, str | Callable[[], str]] = {}


def add(name: str, f: Query, oracle: str | Callable[[], str] | None = None) -> None:
    if name in _queries:
        raise ValueError(f"{name} is there already")
    _queries[name] = f
    if oracle is not None:
        _oracles[name] = oracle


def _load() -> None:
    from corridor.queries import checks, methods, surround, workloads  # noqa: F401


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corridor.queries.workloads import headline

    return headline(spark, sf_dir)


def queries() -> dict[str, Query]:
    _load()
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    _load()
    return {name: sql if isinstance(sql, str) else sql() for name, sql in _oracles.items()}
