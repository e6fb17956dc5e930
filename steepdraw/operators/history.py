"""Last observed gradient lengths: start values, probabilities, deltas, compaction."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def initialise(data: DataFrame, magnitude: Column | float = 1.0) -> DataFrame:
    """history rows from a constant or a length expression over the data (one scan)."""
    value = F.lit(float(magnitude)) if isinstance(magnitude, int | float) else magnitude
    return data.select("instance_id", "shard", value.cast("double").alias("magnitude"), F.lit(0).cast("long").alias("last_step"))


def probabilities(history: DataFrame, beta: float) -> DataFrame:
    """(1 - beta) * share of the total + beta / n; all-zero histories are uniform."""
    if not 0 < beta <= 1:
        raise ValueError("beta must be in (0, 1]; at 0 rows can starve")
    total = history.agg(F.sum("magnitude").alias("_total"), F.count(F.lit(1)).alias("_n"))
    share = F.when(F.col("_total") > 0, F.col("magnitude") / F.col("_total")).otherwise(1.0 / F.col("_n"))
    return history.join(F.broadcast(total)).withColumn("prob", (1 - beta) * share + beta / F.col("_n")).drop("_total", "_n")


def compact(history: DataFrame, deltas: DataFrame) -> DataFrame:
    """Latest length of each row: deltas are appended, then merged by one aggregation."""
    both = history.unionByName(deltas)
    return both.groupBy("instance_id").agg(F.max_by("shard", "last_step").alias("shard"), F.max_by("magnitude", "last_step").alias("magnitude"), F.max("last_step").alias("last_step"))


def attach(data: DataFrame, history: DataFrame, default: float = 1.0) -> DataFrame:
    """Data with stored lengths, `default` where a row was never seen."""
    own = history.select("instance_id", "magnitude", "last_step")
    return data.join(own, "instance_id", "left").withColumn("magnitude", F.coalesce("magnitude", F.lit(default)))


def staleness(history: DataFrame, step: int) -> DataFrame:
    age = F.lit(step) - F.col("last_step")
    return history.agg(F.avg(age).alias("mean_age"), F.percentile_approx(age, 0.5).alias("median_age"), F.max(age).alias("max_age"))
