"""All questions, by name, and the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

MODULES = ("static", "indexed", "changing", "operators", "measures")


def _modules():
    return [import_module(f"{__name__}.{m}") for m in MODULES]


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: q for m in _modules() for k, q in m.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {k: q for m in _modules() for k, q in m.ORACLES.items()}
