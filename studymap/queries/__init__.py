"""Registry of named queries: each is (Spark callable, DuckDB SQL or None)."""

from __future__ import annotations

import importlib
from collections.abc import Callable
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession

MODULES = ("orders_q", "models_q", "heads_q", "network_q", "generic_q", "corpora_q")


class Query(NamedTuple):
    run: Callable[[SparkSession, str], DataFrame]
    sql: str | None


_FOUND: dict[str, Query] = {}


def query(name: str, sql: str | None = None):
    """Register a (spark, sf_dir) -> DataFrame callable under `name`."""

    def keep(f):
        if name in _FOUND:
            raise ValueError(f"query {name} is registered twice")
        _FOUND[name] = Query(f, sql)
        return f

    return keep


def registry() -> dict[str, Query]:
    for m in MODULES:
        importlib.import_module(f"{__name__}.{m}")
    return dict(_FOUND)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
