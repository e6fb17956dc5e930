"""Online training and windowed measures over an event stream."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.features import shard_of
from ..functions.objectives import Linear
from ..functions.steps import StepRule, constant
from ..plans import trainers as T
from ..sources.tables import checkpointed, scratch

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """The events table as a file stream; ts becomes a timestamp, as watermarks need."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", per_trigger).parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(events: DataFrame, every: str = "1 day", late: str = "10 minutes") -> DataFrame:
    """Count, mean and greatest value by tumbling window and type; late rows are dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", every), "event_type").agg(F.count(F.lit(1)).alias("n"), F.avg("value").alias("mean"), F.max("value").alias("top"))


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "10 minutes").groupBy(F.window("ts", width, slide), "event_type").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", gap).alias("session"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("value"))


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join by user."""
    return events.join(customers, events.user_id == customers.c_custkey, "left")


def follow_ups(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: purchases of the same user within an interval after a click."""
    a = clicks.withWatermark("ts", "10 minutes").select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = purchases.withWatermark("ts", "10 minutes").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}"))


MOST = (1 << 63) - 1  # stands for a missing time or id, which SQL orders last


def user_lengths(events: DataFrame) -> DataFrame:
    """Latest value and number of visits of each user, kept as state across batches.

    The latest is the row with the greatest (ts, event_id) that has a value, in whatever order and
    pieces the rows of a user arrive.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, at, event, last = state.get if state.exists else (0, None, None, None)
        for pdf in batches:
            n += len(pdf)
            known = np.flatnonzero(pdf["known"].to_numpy())
            if len(known):
                when, ids = pdf["at"].to_numpy()[known], pdf["event_id"].to_numpy()[known]
                top = np.lexsort((ids, when))[-1]
                found = int(when[top]), int(ids[top])
                if at is None or found >= (at, event):
                    (at, event), last = found, float(pdf["value"].to_numpy()[known[top]])
        state.update((n, at, event, last))
        yield pd.DataFrame({"user_id": pd.array([key[0]], dtype="Int64"), "visits": [n], "magnitude": pd.array([last], dtype="Float64")})

    at = F.coalesce(F.unix_micros(F.col("ts").cast("timestamp")), F.lit(MOST))
    own = events.select("user_id", at.alias("at"), F.coalesce("event_id", F.lit(MOST)).alias("event_id"), "value", F.col("value").isNotNull().alias("known"))
    return own.groupBy("user_id").applyInPandasWithState(update, "user_id long, visits long, magnitude double", "visits long, at long, event long, magnitude double", "update", "NoTimeout")


def run_available(df: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Everything available now, written by the tasks to files; checkpointed, so a restart goes on.

    Complete results replace those of the batch before, others go into a folder for each batch, which
    a replayed batch overwrites.
    """
    spark, path = df.sparkSession, scratch(df.sparkSession, f"rows-{name}")
    spark.createDataFrame([], df.schema).write.parquet(f"{path}/0")  # there may be no batch

    def keep(rows: DataFrame, batch_id: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/{0 if mode == 'complete' else batch_id + 1}")

    query = df.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", scratch(spark, f"stream-{name}")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).option("recursiveFileLookup", "true").parquet(path)


class PrequentialTrainer:
    """Scores each batch first, then takes weighted steps on it; the model persists between batches.

    All rows of a micro-batch are scored, by a distributed mean, and all can be drawn: by shard
    masses, from the lengths of its own rows under the current model, mixed with a uniform floor.
    Only the drawn rows (steps times batch) reach the driver; the batch id seeds the draws, so a
    replayed batch gives the same model.
    """

    def __init__(self, dim: int, rule: StepRule | None = None, steps: int = 20, batch: int = 32, beta: float = 0.2) -> None:
        self.objective, self.rule = Linear("squared", dim), rule or constant(0.01)
        self.w, self.steps, self.batch, self.beta = np.zeros(dim), steps, batch, beta
        self.trace: list[tuple[int, int, float, float]] = []

    def _score(self, data: DataFrame) -> tuple[int, float]:
        """Number of rows and mean loss under the current model."""
        objective, w = self.objective, self.w

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                if len(pdf):
                    x, y = np.array(pdf["features"].tolist()), pdf["label"].to_numpy(dtype=float)
                    yield pd.DataFrame({"n": [len(pdf)], "loss": [float(objective.evaluate(w, x, y)[0].sum())]})

        r = data.select("features", "label").mapInPandas(run, "n long, loss double").agg(F.sum("n").alias("n"), F.sum("loss").alias("loss")).first()
        return (r["n"], r["loss"] / r["n"]) if r["n"] else (0, 0.0)

    def __call__(self, df: DataFrame, batch_id: int) -> None:
        # an id that repeats is numbered, so that each row is drawn for itself
        again = F.row_number().over(Window.partitionBy("instance_id").orderBy(F.xxhash64("features", "label")))
        key = F.concat_ws("#", F.col("instance_id").cast("string"), again.cast("string"))
        own = df.select(key.alias("instance_id"), "features", "label").withColumns({"shard": shard_of(F.col("instance_id"), 16), "is_valid": F.lit(False)})
        own = checkpointed(own, "micro-batch")
        n, before = self._score(own)
        if not n:
            return
        done = T.train("history", own, self.objective, w=self.w, steps=self.steps, batch=self.batch, step_rule=self.rule, seed=batch_id, exec_mode=f"prefetch:{self.steps}", beta=self.beta, init="exact_scan")
        self.w = done.model
        self.trace.append((batch_id, n, before, self._score(own)[1]))


def event_instances(events: DataFrame) -> DataFrame:
    """Rows a prequential trainer reads: hour, type flags, counter, constant; label: value / 50."""
    types = ["click", "purchase", "search", "signup", "view"]
    k = F.coalesce(F.from_json("props", "k int")["k"].cast("double"), F.lit(0.0)) / 100.0
    features = F.array((F.hour("ts") / 24.0).cast("double"), *[(F.col("event_type") == t).cast("double") for t in types], k, F.lit(1.0))
    return events.select(F.col("event_id").alias("instance_id"), features.alias("features"), (F.col("value") / 50.0).alias("label"))


def stream_window_loss(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = run_available(windowed(event_stream(spark, sf_dir)), "stream_window_loss")
    return out.select(F.date_format(F.col("window.start"), "yyyy-MM-dd").alias("day"), "event_type", "n", F.round("mean", 5).alias("mean"), F.round("top", 4).alias("top"))


def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = run_available(sessions(event_stream(spark, sf_dir)), "stream_session")
    return out.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest"))


def stream_user_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = run_available(user_lengths(event_stream(spark, sf_dir)), "stream_user_state", "update")
    last = out.groupBy("user_id").agg(F.max_by("magnitude", "visits").alias("magnitude"), F.max("visits").alias("visits"))
    return last.select("user_id", "visits", F.round("magnitude", 4).alias("magnitude"))


def stream_follow_ups(spark: SparkSession, sf_dir: str) -> DataFrame:
    ev = event_stream(spark, sf_dir)
    out = run_available(follow_ups(ev.where("event_type = 'click'"), event_stream(spark, sf_dir).where("event_type = 'purchase'")), "stream_follow_ups", "append")
    return out.groupBy(F.col("u1").alias("user_id")).agg(F.count(F.lit(1)).alias("pairs"))


def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_mktsegment")
    out = run_available(with_customers(event_stream(spark, sf_dir), customers).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "stream_static")
    return out.select("c_mktsegment", "n")


def stream_prequential(spark: SparkSession, sf_dir: str) -> DataFrame:
    trainer = PrequentialTrainer(8)
    query = event_instances(event_stream(spark, sf_dir)).writeStream.foreachBatch(trainer).option("checkpointLocation", scratch(spark, "prequential")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.createDataFrame([(b, n, round(x, 6), round(y, 6)) for b, n, x, y in trainer.trace], "batch long, rows int, loss_before double, loss_after double")


def queries() -> dict[str, tuple]:
    gap = "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM e), g AS (SELECT user_id, sid, count(*) AS n FROM s GROUP BY ALL) SELECT user_id, count(*) AS sessions, sum(n)::BIGINT AS events, max(n) AS longest FROM g GROUP BY 1"
    return {
        "stream_window_loss": (stream_window_loss, "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n, round(avg(value), 5) AS mean, round(max(value), 4) AS top FROM events GROUP BY 1, 2"),
        "stream_session": (stream_session, gap),
        "stream_user_state": (stream_user_state, "SELECT user_id, count(*) AS visits, round(arg_max(value, (ts, event_id)), 4) AS magnitude FROM events GROUP BY 1"),
        "stream_follow_ups": (stream_follow_ups, "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase' GROUP BY 1"),
        "stream_static": (stream_static, "SELECT c_mktsegment, count(*) AS n FROM events LEFT JOIN customer ON user_id = c_custkey GROUP BY 1"),
        "stream_prequential": (stream_prequential, None),
    }
