"""Readers and writers: declared columns only, so scans stay pruned."""

from __future__ import annotations

import atexit
import gc
import shutil
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, fmt: str, schema: T.StructType | str, **options: str) -> DataFrame:
    """CSV, JSON, ORC, Parquet or text with a stated schema; nothing is inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def register_views(spark: SparkSession, sf_dir: str) -> None:
    for name in TABLES:
        read_table(spark, sf_dir, name).createOrReplaceTempView(name)


ROW_GROUP = 16 << 20


def write_sharded(df: DataFrame, path: str, shards: int, key: str = "instance_id") -> None:
    """One shuffle: a folder for each shard, rows sorted by key, so a stage is a pruned read.

    Row groups are small, so that several tasks share the read of one shard.
    """
    (df.repartition(shards, "shard").sortWithinPartitions("shard", key).write.mode("overwrite").option("parquet.block.size", ROW_GROUP).partitionBy("shard").parquet(path))


def write_history(df: DataFrame, name: str, buckets: int, key: str = "instance_id") -> None:
    """Bucketed and sorted by row id: later joins with co-bucketed data need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)


def save_model(spark: SparkSession, path: str, step: int, layers: list, stage: int = 0) -> None:
    rows = [(step, stage, i, int(a.shape[0]), int(a.shape[1]) if a.ndim > 1 else 1, [float(v) for v in a.ravel()]) for i, a in enumerate(layers)]
    spark.createDataFrame(rows, "step long, stage int, layer int, rows int, cols int, values array<double>").coalesce(1).write.mode("append").parquet(path)


def append_trace(trace: DataFrame, path: str) -> None:
    trace.coalesce(1).write.mode("append").parquet(path)


def time_action(df: DataFrame) -> float:
    """Seconds to run the whole plan into a null sink."""
    import time

    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the folder that driver and executors share."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and spark.sparkContext.master.startswith("local["):
        folder = f"/tmp/checkpoints/{spark.sparkContext.applicationId}"
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        root = f"file://{folder}"
    elif not root:
        root = spark.conf.get("spark.sql.warehouse.dir") + "/_scratch"
    return f"{root.rstrip('/')}/{label}-{uuid.uuid4().hex}"


def checkpointed(df: DataFrame, label: str = "state") -> DataFrame:
    """Lineage cut by a written table: survives lost executors."""
    path = scratch(df.sparkSession, label)
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def only_reads(df: DataFrame) -> bool:
    """Whether df is columns and rows of written files and nothing else, so that a copy would save no work."""
    nodes = [df._jdf.queryExecution().optimizedPlan()]
    while nodes:
        node = nodes.pop()
        if node.nodeName() not in ("Project", "Filter") and not node.getClass().getSimpleName() == "LogicalRelation":
            return False
        nodes += [node.children().apply(i) for i in range(node.children().size())]
    return True


def dropped(df: DataFrame) -> None:
    """Deletes a scratch table that another has replaced; nothing may read it any more."""
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        own = path(folder)
        own.getFileSystem(spark._jsc.hadoopConfiguration()).delete(own, True)
    collected(spark)


def collected(spark: SparkSession) -> None:
    """Shuffle files of jobs that are over go when the driver's heap is collected, which by itself may be long after."""
    gc.collect()
    spark._jvm.System.gc()


def sharded(df: DataFrame, label: str = "instances", shards: int = 16) -> DataFrame:
    """Rows in a folder for each shard, so reading a shard reads its folder only."""
    path = scratch(df.sparkSession, label)
    write_sharded(df, path, shards)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def no_nulls(df: DataFrame, columns: list[str]) -> DataFrame:
    """Rows with all of the columns present; training rejects the others."""
    keep = F.lit(True)
    for c in columns:
        keep = keep & F.col(c).isNotNull()
    return df.where(keep)
