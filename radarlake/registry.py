"""The registered queries of the library and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]
MODULES = ("selection", "resampling", "geometry", "optical", "captions", "release", "physics", "relational", "functions", "catalogue", "streams", "studies", "generation")
_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    """Registers a query under its function's name; `sql` is DuckDB text for the same rows."""

    def add(f: Query) -> Query:
        key = name or f.__name__
        if key in _queries:
            raise ValueError(f"{key} is registered twice")
        _queries[key] = f
        if sql is not None:
            _oracles[key] = sql
        return f

    return add


def known() -> dict[str, str]:
    """The SQL that modules loaded so far have registered."""
    return dict(_oracles)


def _load() -> None:
    for m in MODULES:
        import_module(f"radarlake.queries.{m}")


def queries() -> dict[str, Query]:
    _load()
    return dict(_queries)


def oracles() -> dict[str, str]:
    _load()
    return dict(_oracles)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    from radarlake import pipeline

    return pipeline.build(spark, sf_dir)
