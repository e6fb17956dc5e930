"""Streams: late rows, restarts, state across batches, the online trainer."""

import datetime as dt

import numpy as np
from pyspark.sql import functions as F

from steepdraw.streaming import online

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event(i, hour, user=1, value=1.0, day=1):
    return (i, dt.datetime(2024, 1, day, hour), user, "click", value, '{"k": 1}')


def write(spark, path, name, rows):
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(f"{path}/{name}")


def source(spark, path):
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 1).parquet(f"{path}/*")


def test_late_rows_are_dropped_and_a_restart_goes_on(spark, tmp_path):
    data, out, check = (f"file://{tmp_path}/{x}" for x in ("data", "out", "check"))

    def run():
        counts = online.windowed(source(spark, data), "1 hour", "10 minutes").select("window.start", "n")
        counts.writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
        return {r.start.hour: r.n for r in spark.read.parquet(out).collect()}

    write(spark, data, "a", [event(1, 1), event(2, 1), event(3, 5)])
    assert run() == {1: 2}
    write(spark, data, "b", [event(4, 1), event(5, 5), event(6, 9)])  # the first is too late
    assert run() == {1: 2, 5: 2}


def test_state_is_kept_between_batches(spark, tmp_path):
    data = f"file://{tmp_path}/data"
    write(spark, data, "a", [event(1, 1, 7, 2.0), event(2, 2, 8, 3.0)])
    write(spark, data, "b", [event(3, 3, 7, 5.0)])
    out = online.run_available(online.user_lengths(source(spark, data)), "state_test", "update")
    last = {r.user_id: (r.visits, r.magnitude) for r in out.orderBy("visits").collect()}
    assert last == {7: (2, 5.0), 8: (1, 3.0)}


def test_latest_value_in_any_order_and_pieces(spark, tmp_path):
    data = f"file://{tmp_path}/data"
    write(spark, data, "a", [event(1, 9, 7, 9.0), event(2, 3, 7, 3.0), event(3, 1, 7, 1.0), event(4, 12, 7, None), event(5, 1, 8, None), event(6, 1, None, 4.0)])
    write(spark, data, "b", [event(7, 5, 7, 5.0)])  # older than what has been seen
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1")
    try:
        out = online.run_available(online.user_lengths(source(spark, data)), "order_test", "update").collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    last = {r.user_id: (r.visits, r.magnitude) for r in sorted(out, key=lambda r: r.visits)}
    assert last == {7: (5, 9.0), 8: (1, None), None: (1, 4.0)}


def test_repeats_within_the_watermark_are_dropped(spark, tmp_path):
    data = f"file://{tmp_path}/data"
    write(spark, data, "a", [event(1, 1), event(1, 1), event(2, 1)])
    assert online.run_available(online.deduplicated(source(spark, data)), "dedup_test", "append").count() == 2


def test_results_of_streams_lie_in_files_not_on_the_driver(spark, tmp_path):
    data = f"file://{tmp_path}/data"
    write(spark, data, "a", [event(1, 1, 7), event(2, 2, 8)])
    write(spark, data, "b", [event(3, 3, 7), event(4, 20, 7)])
    whole = online.run_available(online.sessions(source(spark, data)), "files_whole")
    assert whole.inputFiles() and sorted((r.user_id, r.n) for r in whole.collect()) == [(7, 1), (7, 2), (8, 1)]
    each = online.run_available(online.user_lengths(source(spark, data)), "files_each", "update")
    assert each.inputFiles() and sorted((r.user_id, r.visits) for r in each.collect()) == [(7, 1), (7, 3), (8, 1)]
    assert online.run_available(source(spark, data).where("user_id = 9"), "files_none", "append").count() == 0


def test_trainer_is_replayed_exactly(spark):
    rng = np.random.default_rng(0)
    rows = [(i, [float(v) for v in x], float(x @ [1.0, -2.0])) for i, x in enumerate(rng.standard_normal((200, 2)))]
    df = spark.createDataFrame(rows, "instance_id long, features array<double>, label double")
    models = []
    for parts in (1, 5):
        t = online.PrequentialTrainer(2, steps=50)
        t(df.repartition(parts), 3)
        models.append(t.w)
        assert t.trace[0][3] < t.trace[0][2]
    assert np.allclose(models[0], models[1])


def test_prequential_trainer_scores_every_row(spark):
    n = 30_000
    df = spark.range(n).select(F.col("id").alias("instance_id"), F.array(F.lit(1.0), (F.col("id") / n).cast("double")).alias("features"), F.when(F.col("id") % 3 == 0, 2.0).otherwise(1.0).alias("label"))
    t = online.PrequentialTrainer(2, steps=5)
    t(df, 1)
    assert t.trace[0][1] == n and np.isclose(t.trace[0][2], 2.0)


def test_sliding_windows_count_each_event_twice(spark, tmp_path):
    data = f"file://{tmp_path}/data"
    write(spark, data, "a", [event(1, 1, day=2), event(2, 1, day=3)])
    out = online.run_available(online.sliding(source(spark, data)), "sliding_test")
    assert out.agg(F.sum("n")).first()[0] == 4
