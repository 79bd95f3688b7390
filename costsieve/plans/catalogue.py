"""Registry of the engine's queries and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def register(name: str, query: Query, oracle: str | None = None) -> None:
    if name in _QUERIES:
        raise ValueError(f"query {name} is registered twice")
    _QUERIES[name] = query
    if oracle is not None:
        _ORACLES[name] = oracle


def _defined() -> None:
    from . import definitions  # noqa: F401  registers everything on import


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    _defined()
    return _QUERIES["chf_wfpr_by_method"](spark, sf_dir)


def queries() -> dict[str, Query]:
    _defined()
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    _defined()
    return dict(_ORACLES)
