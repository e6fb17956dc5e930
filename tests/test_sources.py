"""Sinks and readers: pruned stages, co-bucketed joins, stated schemas."""

import numpy as np
from pyspark.sql import functions as F

from steepdraw.operators import history as H
from steepdraw.sources import tables as S


def test_a_stage_reads_its_shard_only(spark, tmp_path):
    path = f"file://{tmp_path}/sharded"
    S.write_sharded(spark.range(1000).select(F.col("id").alias("instance_id"), (F.col("id") % 8).cast("int").alias("shard")), path, 8)
    stage = spark.read.parquet(path).where("shard = 3")
    assert stage.count() == 125
    assert "PartitionFilters: [isnotnull(shard" in stage._jdf.queryExecution().toString()


def test_bucketed_history_joins_without_a_shuffle(spark):
    rows = spark.range(500).select(F.col("id").cast("string").alias("instance_id"), F.lit(0).alias("shard"), F.lit(1.0).alias("magnitude"), F.lit(1).cast("long").alias("last_step"))
    for name in ("bucketed_a", "bucketed_b"):
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        S.write_history(rows, name, 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        joined = H.attach(spark.table("bucketed_a").drop("magnitude", "last_step"), spark.table("bucketed_b"))
        assert "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
        assert joined.count() == 500
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        for name in ("bucketed_a", "bucketed_b"):
            spark.sql(f"DROP TABLE IF EXISTS {name}")


def test_readers_models_and_traces(spark, tmp_path):
    path = f"file://{tmp_path}"
    spark.createDataFrame([(1, "a"), (2, None)], "k int, v string").write.csv(f"{path}/csv")
    assert S.no_nulls(S.read_any(spark, f"{path}/csv", "csv", "k int, v string"), ["v"]).count() == 1
    S.save_model(spark, f"{path}/model", 5, [np.arange(6.0).reshape(2, 3), np.ones(2)])
    got = {r.layer: (r.rows, r.cols, list(r["values"])) for r in spark.read.parquet(f"{path}/model").collect()}
    assert got == {0: (2, 3, [0.0, 1.0, 2.0, 3.0, 4.0, 5.0]), 1: (2, 1, [1.0, 1.0])}
    S.append_trace(spark.range(2).toDF("step"), f"{path}/trace")
    S.append_trace(spark.range(3).toDF("step"), f"{path}/trace")
    assert spark.read.parquet(f"{path}/trace").count() == 5
    assert S.time_action(spark.range(10)) > 0
    assert S.checkpointed(spark.range(4)).count() == 4
