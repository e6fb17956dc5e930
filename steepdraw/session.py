"""Session settings that suit the engine; a session that already runs is used as it is."""

from __future__ import annotations

import os

from pyspark.sql import SparkSession


def session(app: str = "steepdraw", cpus: int | None = None, **extra: str) -> SparkSession:
    """Adaptive execution on, Arrow on, shuffle partitions by cores for local masters."""
    cpus = cpus or os.cpu_count() or 4
    conf = {
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.adaptive.skewJoin.enabled": "true",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
        "spark.sql.shuffle.partitions": str(2 * cpus),
        "spark.sql.session.timeZone": "UTC",
        "spark.ui.enabled": "false",
    } | extra
    builder = SparkSession.builder.appName(app).master(extra.pop("spark.master", f"local[{cpus}]"))
    for k, v in conf.items():
        builder = builder.config(k, v)
    return builder.getOrCreate()
