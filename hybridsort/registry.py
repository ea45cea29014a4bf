"""Every query of the sorting engine by name, with its SQL where SQL can state it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import queries_around, queries_more, queries_sort


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return queries_sort.QUERIES | queries_around.QUERIES | queries_more.QUERIES


def oracle_sql() -> dict[str, str]:
    return queries_sort.SQL | queries_around.SQL | queries_more.SQL
