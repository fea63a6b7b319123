"""Registered queries of the search engine and their DuckDB counterparts."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
_REPO = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def query(name: str, sql: str | None = None):
    """Register a query f(spark, sf_dir), with its SQL where SQL can express it."""

    def add(f):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            env = spark.sparkContext.environment  # workers must find the package even when it is not installed
            if _REPO not in env.get("PYTHONPATH", ""):
                env["PYTHONPATH"] = os.pathsep.join(x for x in (env.get("PYTHONPATH"), _REPO) if x)
            return f(spark, sf_dir)

        QUERIES[name] = run
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _load() -> None:
    from .plans import q_corpus, q_graphs, q_relational, q_relational2, q_search, q_vectors, workloads  # noqa: F401


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    _load()
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    _load()
    return dict(ORACLES)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nearest chunks of each benchmark item by interleaved search, with the number of encoded objects."""
    _load()
    return QUERIES["interleaved_alpha"](spark, sf_dir)
