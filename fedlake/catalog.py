"""All queries of the engine by name."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from fedlake.queries.registry import REGISTRY

AREAS = ("data", "privacy", "training", "sequences", "ranking", "models", "streams", "udfs")


def _load() -> None:
    for area in AREAS:
        importlib.import_module(f"fedlake.queries.{area}")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    _load()
    return {name: q.run for name, q in REGISTRY.items()}


def oracle_sql() -> dict[str, str]:
    _load()
    return {name: q.sql for name, q in REGISTRY.items() if q.sql is not None}
