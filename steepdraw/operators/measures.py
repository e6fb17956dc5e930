"""Variance, bias, staleness, iterations and time: what the methods are judged by."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import columns as C


def scored(df: DataFrame, features: list[str], w: list[float], kind: str) -> DataFrame:
    """Adds score, loss, slope and len (gradient length) of a linear model."""
    xs = [F.col(c) for c in features]
    out = df.withColumn("score", C.dot(xs, w)).withColumn("sq", C.sq_norm(xs))
    s, y = F.col("score"), F.col("label")
    return out.withColumns({"loss": C.loss(kind, s, y), "slope": C.slope(kind, s, y)}).withColumn("len", F.abs("slope") * F.sqrt("sq"))


def empirical_risk(df: DataFrame) -> DataFrame:
    return df.agg(F.avg("loss").alias("risk"))


def full_gradient(df: DataFrame, features: list[str]) -> DataFrame:
    """One row g_<feature>: the mean gradient, summed map side."""
    return df.agg(*[F.avg(F.col("slope") * F.col(c)).alias(f"g_{c}") for c in features])


def _sums(df: DataFrame, features: list[str], prob: Column | None) -> DataFrame:
    inverse = [F.sum(F.col("len") * F.col("len") / prob).alias("inv")] if prob is not None else []
    return df.agg(F.count(F.lit(1)).alias("n"), F.sum("len").alias("s1"), F.sum(F.col("len") * F.col("len")).alias("s2"), *inverse, *[F.avg(F.col("slope") * F.col(c)).alias(f"g_{c}") for c in features])


def variance_report(df: DataFrame, features: list[str], prob: Column | None = None, batch: int = 1) -> DataFrame:
    """Variance of the stochastic gradient under uniform, least possible and given probabilities.

    One pass: the least variance needs only sums of lengths and squared lengths.
    """
    s = _sums(df, features, prob)
    g = sum((F.col(f"g_{c}") * F.col(f"g_{c}") for c in features), F.lit(0.0))
    n = F.col("n")
    uniform, least = (F.col("s2") / n - g) / batch, (F.col("s1") / n * (F.col("s1") / n) - g) / batch
    out = [n.alias("n"), uniform.alias("var_uniform"), least.alias("var_least"), F.when(uniform <= 1e-15, 1.0).otherwise(least / uniform).alias("ratio_least")]
    if prob is not None:
        given = (F.col("inv") / (n * n) - g) / batch
        out += [given.alias("var_given"), F.when(uniform <= 1e-15, 1.0).otherwise(given / uniform).alias("ratio_given"), F.when(given <= 1e-15, 1.0).otherwise(uniform / given).alias("equal_batch")]
    return s.select(*out)


def bias_norm(df: DataFrame, features: list[str], prob: Column, reweight: bool = True) -> DataFrame:
    """Length of (expected stochastic gradient - full gradient); zero up to rounding if re-weighted."""
    n = df.agg(F.count(F.lit(1)).alias("_n"))
    wide = df.join(F.broadcast(n))
    weight = 1.0 / (F.col("_n") * prob) if reweight else F.lit(1.0)
    parts = [(F.sum(prob * weight * F.col("slope") * F.col(c)) - F.avg(F.col("slope") * F.col(c))).alias(c) for c in features]
    return wide.agg(*parts).select(F.sqrt(sum((F.col(c) * F.col(c) for c in features), F.lit(0.0))).alias("bias_norm"))


def weighted_length_spread(df: DataFrame, prob: Column) -> DataFrame:
    """Least, greatest and mean length of re-weighted gradients; all equal at the best probabilities."""
    n = df.agg(F.count(F.lit(1)).alias("_n"))
    step = F.col("len") / (F.col("_n") * prob)
    return df.join(F.broadcast(n)).agg(F.min(step).alias("least"), F.max(step).alias("greatest"), F.avg(F.col("len")).alias("mean_length"))


def gain_columns(df: DataFrame, step: int | Column, gain: str = "entropy") -> DataFrame:
    """uncertainty, significance (row norm), interval since the last visit, and their product."""
    p = C.probability(F.col("score"), F.lit(1.0))
    uncertain = C.entropy(p) if gain == "entropy" else 2.0 * p * (1.0 - p)
    since = (F.lit(step) if isinstance(step, int) else step) - F.coalesce(F.col("last_step"), F.lit(0)) if "last_step" in df.columns else F.lit(1)
    out = df.withColumns({"uncertainty": uncertain, "significance": F.sqrt("sq"), "interval": since})
    return out.withColumn("gain", F.col("uncertainty") * F.col("significance") * F.col("interval"))


def visit_table(draws: DataFrame) -> DataFrame:
    return draws.groupBy("instance_id").agg(F.count(F.lit(1)).alias("visits"), F.max("step").alias("last_step"))


def confusion(df: DataFrame) -> DataFrame:
    predicted = F.when(F.col("score") >= 0, 1).otherwise(-1)
    return df.groupBy(F.col("label").cast("int").alias("label")).agg(F.count(F.when(predicted == 1, 1)).alias("predicted_pos"), F.count(F.when(predicted == -1, 1)).alias("predicted_neg"))


def steps_to(trace: DataFrame, target: float) -> DataFrame:
    """First step of each (method, seed) with error at or below the target; null if never."""
    return trace.groupBy("method", "seed").agg(F.min(F.when(F.col("error") <= target, F.col("step"))).alias("steps"), F.min(F.when(F.col("error") <= target, F.col("elapsed_s"))).alias("seconds"))


def seconds_per_step(trace: DataFrame) -> DataFrame:
    return trace.groupBy("method").agg((F.sum("elapsed_s") / F.sum("step")).alias("s_per_step"))


def overhead(trace: DataFrame, base: str) -> DataFrame:
    """Seconds per step over the base method's, less one; and the speed-up in time at equal steps."""
    each = trace.groupBy("method", "seed").agg(F.max("step").alias("step"), F.max("elapsed_s").alias("elapsed_s"))
    per = seconds_per_step(each)
    own = per.where(F.col("method") == base).select(F.col("s_per_step").alias("base_s"))
    return per.join(F.broadcast(own)).select("method", "s_per_step", (F.col("s_per_step") / F.col("base_s") - 1).alias("overhead"))


def compare_methods(trace: DataFrame, target: float, base: str) -> DataFrame:
    """Per method: mean steps and seconds to the target and their ratios to the base method's,
    runs that never reach it counted with their whole budget, and the mean last error.
    """
    ends = trace.groupBy("method", "seed").agg(F.max("step").alias("last"), F.max("elapsed_s").alias("whole"), F.max_by("error", "step").alias("error"))
    hit = steps_to(trace, target).join(ends, ["method", "seed"])
    hit = hit.groupBy("method").agg(F.avg(F.coalesce("steps", "last")).alias("steps"), F.avg(F.coalesce("seconds", "whole")).alias("seconds"), F.count("steps").alias("reached"), F.avg("error").alias("last_error"))
    own = hit.where(F.col("method") == base).select(F.col("steps").alias("base_steps"), F.col("seconds").alias("base_seconds"))
    return hit.join(F.broadcast(own)).select("method", "steps", "seconds", "reached", "last_error", (F.col("steps") / F.col("base_steps")).alias("steps_ratio"), (F.col("base_seconds") / F.col("seconds")).alias("speedup"))


def benefit_share(rows: int, steps: int, batch: int) -> float:
    """Share of a stage's visits that find a length observed within the stage."""
    return max(0.0, 1.0 - rows / (steps * batch))


def length_cost(batch: int, outputs: int, inputs: int) -> float:
    """Extra work of lengths over the gradient's: b (m + l) against b m l."""
    return (outputs + inputs) / (outputs * inputs)
