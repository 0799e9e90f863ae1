"""The operN queries of this folder and their oracles."""

from __future__ import annotations

import importlib
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

MODULES = (
    "ann",
    "langid",
    "warc",
    "secrets",
    "chat",
    "quality",
    "decontaminate",
    "pieces",
    "setjoin",
    "substrings",
)


def _modules():
    return [importlib.import_module(f"hamcover.llm.{name}") for name in MODULES]


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for m in _modules() for name, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in _modules() for name, sql in m.ORACLES.items()}
