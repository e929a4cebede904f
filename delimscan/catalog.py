"""All registered queries of the parsing engine, and the SQL that each must equal."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .plans import experiments, parse_queries, relational, source_queries
from .streaming import event_time


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return parse_queries.Q | relational.Q | source_queries.Q | experiments.Q | event_time.Q


def oracle_sql() -> dict[str, str]:
    return parse_queries.SQL | relational.SQL | source_queries.SQL | experiments.SQL | event_time.SQL
