"""Python-side functions for SQL users: vectorised scoring, gradient sums and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from .columns import py_uniform


def predict(obj, w: np.ndarray):
    """Vectorised scalar function: score of a feature array under a linear model."""

    @F.pandas_udf(DoubleType())
    def score(features: pd.Series) -> pd.Series:
        return pd.Series(np.array(features.tolist()).reshape(len(features), -1) @ w)

    return score


def row_length(obj, w: np.ndarray):
    """Vectorised scalar function: gradient length of (features, label)."""

    @F.pandas_udf(DoubleType())
    def length(features: pd.Series, label: pd.Series) -> pd.Series:
        x = np.array(features.tolist()).reshape(len(features), -1)
        return pd.Series(obj.evaluate(w, x, label.to_numpy(dtype=float))[1])

    return length


def gradient_sum(df: DataFrame, obj, w: np.ndarray) -> DataFrame:
    """(pos, value) of the summed gradient: one partial vector a task, added by position."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros(len(w))
        for pdf in batches:
            if len(pdf):
                x = np.array(pdf["features"].tolist())
                total += obj.evaluate(w, x, pdf["label"].to_numpy(dtype=float))[2](np.ones(len(pdf)))
        yield pd.DataFrame({"pos": np.arange(len(w)), "value": total})

    return df.select("features", "label").mapInPandas(run, "pos int, value double").groupBy("pos").agg(F.sum("value").alias("value"))


@F.udtf(returnType="step int, draw_no int, u double")
class DrawMinibatch:
    """draw_minibatch(seed, step, b): the uniforms of one mini-batch, callable from SQL."""

    def eval(self, seed: int, step: int, b: int):
        for j in range(b):
            yield step, j, py_uniform(seed, step, j)


@F.udtf(returnType="copy int, features array<double>")
class Augment:
    """augment(features, copies): cyclic shifts of a feature array, callable from SQL."""

    def eval(self, features: list, copies: int):
        for c in range(copies):
            k = c % max(1, len(features))
            yield c, list(features[-k:] + features[:-k]) if k else list(features)


def register(spark: SparkSession) -> None:
    spark.udtf.register("draw_minibatch", DrawMinibatch)
    spark.udtf.register("augment", Augment)


def udtf_draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    spark.read.parquet(f"{sf_dir}/supplier.parquet").createOrReplaceTempView("_suppliers")
    return spark.sql("SELECT s_suppkey, draw_no, u FROM _suppliers, LATERAL draw_minibatch(7, s_suppkey, 64)")


def udtf_augment(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark)
    spark.read.parquet(f"{sf_dir}/embeddings.parquet").createOrReplaceTempView("_embeddings")
    return spark.sql("SELECT vec_id, copy, round(a.features[0], 6) AS front FROM _embeddings, LATERAL augment(cast(embedding AS array<double>), 4) a")


def gradient_udaf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .features import as_instances, net_price
    from .objectives import Linear

    data = as_instances(net_price(spark, sf_dir), ["x1", "x2", "x3", "x4", "x0"])
    return gradient_sum(data, Linear("logistic", 5), np.array([4.0, -0.5, 0.3, 0.1, 0.2])).select("pos", F.round("value", 4).alias("g"))


def predict_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .features import as_instances, net_price

    data = as_instances(net_price(spark, sf_dir), ["x1", "x2", "x3", "x4", "x0"])
    score: Column = predict(None, np.array([4.0, -0.5, 0.3, 0.1, 0.2]))("features")
    return data.select(score.alias("s")).agg(F.count(F.when(F.col("s") >= 0, 1)).alias("positive"), F.round(F.avg("s"), 6).alias("mean"))


def queries() -> dict[str, tuple]:
    from ..plans.theory import scored_sql, uniform_sql

    sc = scored_sql("logistic")
    return {
        "udtf_draw_minibatch": (udtf_draws, f"SELECT s_suppkey, j::INTEGER AS draw_no, {uniform_sql('7', 'CAST(s_suppkey AS VARCHAR)', 'CAST(j AS VARCHAR)')} AS u FROM supplier, range(64) r(j)"),
        "udtf_augment": (udtf_augment, "SELECT vec_id, c::INTEGER AS copy, round(embedding[((64 - c) % 64) + 1]::DOUBLE, 6) AS front FROM embeddings, range(4) r(c)"),
        "udaf_gradient_sum": (gradient_udaf, f"WITH {sc} " + " UNION ALL ".join(f"SELECT {i} AS pos, round(sum(slope * {c}), 4) AS g FROM sc" for i, c in enumerate(("x1", "x2", "x3", "x4", "x0")))),
        "udf_predict": (predict_udf, f"WITH {sc} SELECT count(*) FILTER (WHERE s >= 0) AS positive, round(avg(s), 6) AS mean FROM sc"),
    }
