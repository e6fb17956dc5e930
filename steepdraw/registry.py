"""Queries of the training engine and their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .functions import udfs
from .operators import relational
from .plans import theory, workloads
from .streaming import online


def _all() -> dict[str, tuple]:
    return theory.queries() | relational.queries() | udfs.queries() | workloads.queries() | online.queries()


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twenty history-weighted steps on the tabular task, as a trace."""
    return workloads.run_methods(spark, workloads.load_task(spark, sf_dir, "net_price"), 20, methods=("history",), batch=16, eval_every=5)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v[0] for k, v in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {k: v[1] for k, v in _all().items() if v[1]}
