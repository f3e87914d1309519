"""Registered queries of the formula engine and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

Query = Callable[[SparkSession, str], DataFrame]


def _parts() -> list:
    from cellwright.plans import corruption_queries, curation_queries, eval_queries, model_queries, more_queries, surface_queries, task_queries

    return [curation_queries, corruption_queries, task_queries, model_queries, eval_queries, more_queries, surface_queries]


def queries() -> dict[str, Query]:
    return {k: v for p in _parts() for k, v in p.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v for p in _parts() for k, v in p.SQL.items()}
