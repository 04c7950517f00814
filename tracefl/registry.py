"""Queries with the SQL that says the same, kept side by side in the modules that register them."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]

FLAGSHIP = "flagship_private_detector"
MODULES: tuple[str, ...] = ("plans.core", "plans.learning", "plans.probes", "operators.relational", "functions.scalars", "functions.sql_functions", "sources.io", "streaming.event_streams")
_queries: dict[str, Query] = {}
_oracles: dict[str, str] = {}


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    """Registers a function of (spark, sf_dir) under a name, with DuckDB SQL for the same rows if there is such."""

    def add(f: Query) -> Query:
        if name in _queries:
            raise ValueError(f"query {name} is registered twice")
        _queries[name] = f
        if oracle is not None:
            _oracles[name] = oracle
        return f

    return add


def _load() -> None:
    for m in MODULES:
        importlib.import_module(f"tracefl.{m}")


def queries() -> dict[str, Query]:
    _load()
    return dict(_queries)


def oracles() -> dict[str, str]:
    _load()
    return dict(_oracles)
