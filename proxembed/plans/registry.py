"""Names of the driver's queries and their DuckDB texts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from proxembed.plans import exact, runs, surface  # noqa: F401 (surface registers its queries)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sampling until all parts are full, and training, on the geography graph: (vid, part, u, c)."""
    return runs.train_blocked(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return exact.QUERIES | runs.QUERIES


def oracle_sql() -> dict[str, str]:
    return dict(exact.SQL)
