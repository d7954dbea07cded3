"""Registry of the queries outside the text operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import core_queries, experiments, relational
from .streaming import queries as streams


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A batch of role queries over a sweep layout, unit by unit: results equal those of exact search."""
    return core_queries.search_with(spark, sf_dir, "A")[0]


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {**core_queries.Q, **experiments.Q, **relational.Q, **streams.Q}


def oracle_sql() -> dict[str, str]:
    return {**core_queries.SQL, **experiments.SQL, **relational.SQL, **streams.SQL}
