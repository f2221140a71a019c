"""Every query of the library by name, and the SQL that DuckDB runs for it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import workloads
from .plans import dialect, surface, surfaces
from .streaming import streams

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {k: (lambda spark, sf_dir, text=text: dialect.run(spark, sf_dir, text)) for k, text in surface.SHARED.items()} | surfaces.queries() | streams.queries() | workloads.queries()


def oracle_sql() -> dict[str, str]:
    return {k: dialect.oracle(text) for k, text in surface.SHARED.items()} | surfaces.ORACLES | streams.ORACLES | workloads.ORACLES


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.flagship(spark, sf_dir)
