"""All registered queries: name -> Spark function, and name -> DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .queries import imputation, patterns, relational, streams, windows

MODULES = (windows, patterns, imputation, relational, streams)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for m in MODULES for k, v in m.ORACLES.items()}


def flagship(spark: SparkSession, folder: str) -> DataFrame:
    """Supplier weeks imputed end to end: readings with their source."""
    from .plans.pipeline import run_framework
    from .queries.windows import W, wins

    return run_framework(wins(spark, folder), W, runs=2)[0]
