"""The experiments on the given tables: base frames, one query per method or operator, and SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from dagframe.operators import workload_frames as base
from dagframe.operators import workload_graphs, workload_learning, workload_logs, workload_relational

PARTS = (workload_graphs, workload_learning, workload_logs, workload_relational)

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {k: q for part in PARTS for k, q in part.queries().items()}


def oracle_sql() -> dict[str, str]:
    return {k: q for part in PARTS for k, q in part.oracle_sql().items()}


__all__ = ["base", "oracle_sql", "queries"]
