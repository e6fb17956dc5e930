"""Instances from the given tables: keys, standardised features, labels, splits, shards."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import read_table
from .columns import hash_uniform, head_uniforms, py_uniform

NET_PRICE = 50_000.0
LINE_FEATURES = ("l_extendedprice", "l_discount", "l_quantity", "l_tax")


def line_key() -> Column:
    """No shorter set of columns is unique at every size; the price goes in as whole cents."""
    return F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long"))


def standardise(df: DataFrame, columns: list[str], stats: DataFrame | None = None) -> DataFrame:
    """Columns minus mean over population deviation; the statistics are one broadcast row."""
    if stats is None:
        stats = df.agg(*[F.avg(c).alias(f"avg_{c}") for c in columns], *[F.stddev_pop(c).alias(f"std_{c}") for c in columns])
    wide = df.join(F.broadcast(stats))
    keep = [c for c in df.columns if c not in columns]
    return wide.select(*keep, *[((F.col(c) - F.col(f"avg_{c}")) / F.col(f"std_{c}")).alias(c) for c in columns])


def hash_split(key: Column, valid_pct: int, salt: str = "split") -> Column:
    return hash_uniform(salt, key) < valid_pct / 100.0


def shard_of(key: Column, shards: int) -> Column:
    return F.floor(hash_uniform("shard", key) * shards).cast("int")


def net_price(spark: SparkSession, sf_dir: str, extra: tuple[str, ...] = ()) -> DataFrame:
    """instance_id, x1..x4 (price, discount, quantity, tax), x0 = 1, label: net price above a bound."""
    lines = read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", *LINE_FEATURES, *extra])
    net = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    own = lines.select(line_key().alias("instance_id"), *LINE_FEATURES, *extra, F.when(net > NET_PRICE, 1.0).otherwise(-1.0).alias("label"), net.alias("net"))
    out = standardise(own, list(LINE_FEATURES))
    return out.select("instance_id", *[F.col(c).alias(f"x{i + 1}") for i, c in enumerate(LINE_FEATURES)], F.lit(1.0).alias("x0"), "label", "net", *extra)


def as_instances(df: DataFrame, features: list[str], shards: int = 16, valid_pct: int = 20) -> DataFrame:
    """The canonical schema: instance_id, shard, is_valid, features, label."""
    key = F.col("instance_id")
    return df.select("instance_id", shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), F.array(*[F.col(c).cast("double") for c in features]).alias("features"), F.col("label").cast("double").alias("label"))


def planted_directions(dim: int, classes: int, seed: int) -> np.ndarray:
    """Directions from hashes, the same in every engine."""
    return np.array([[py_uniform("planted", seed, c, j) - 0.5 for j in range(dim)] for c in range(classes)])


def shifted(x: np.ndarray, source: list, copy: np.ndarray) -> np.ndarray:
    """Rows of x turned by 0 to 3 places, jittered and scaled to length 1, as copy `copy` of row `source`.

    The jitter is hash_uniform("jitter", source, copy, place), without the source where it is null.
    """
    heads = [f"jitter:{c}:".encode() if v is None else f"jitter:{v}:{c}:".encode() for v, c in zip(source, copy.tolist(), strict=True)]
    moved = x + (head_uniforms(heads, x.shape[1]) - 0.5) * 0.02
    for turn in range(1, 4):  # small cyclic shifts leave most of the signal
        own = copy % 4 == turn
        moved[own] = np.roll(moved[own], turn, axis=1)
    return moved / np.sqrt(np.add.accumulate(moved * moved, axis=1)[:, -1:])


def _shifted(copies: int):
    """All copies of rows of (vec_id, x, label)."""

    def run(batches):
        every = np.arange(copies)
        for batch in batches:
            for i in range(batch.num_rows):
                own, x, label = (batch.column(c)[i].as_py() for c in ("vec_id", "x", "label"))
                ids = [None if own is None else own * copies + c for c in range(copies)]
                if x is None or None in x:
                    features = pa.array([None if x is None else [None] * len(x)] * copies, pa.list_(pa.float64()))
                else:
                    made = shifted(np.tile(np.array(x), (copies, 1)), [own] * copies, every)
                    features = pa.ListArray.from_arrays(np.arange(copies + 1, dtype=np.int32) * len(x), made.ravel())
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), features, pa.array([label] * copies, pa.float64())], names=["vec_id", "x", "label"])

    return run


def planted_embeddings(spark: SparkSession, sf_dir: str, classes: int = 10, seed: int = 7, shards: int = 16, valid_pct: int = 20, copies: int = 1, late: bool = False) -> DataFrame:
    """Embeddings with a label that their direction decides; copies are shifted and jittered.

    With `late`, a copy is a row of its source's values, `source` and `copy`: whoever trains on it makes
    its features (`shifted`) when they are read, so 128 copies don't take 128 times the disk.
    """
    own = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    table = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in planted_directions(64, classes, seed)])
    score = F.transform(table, lambda d: F.aggregate(F.zip_with("x", d, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v))
    out = own.select("vec_id", "embedding", F.col("embedding").cast("array<double>").alias("x")).withColumn("score", score)
    label = (F.array_position("score", F.array_max("score")) - 1).cast("double") if classes > 2 else F.when(F.get("score", F.lit(0)) >= 0, 1.0).otherwise(-1.0)
    out = out.select("vec_id", "embedding" if late else "x", label.alias("label"))
    if late:
        each = out.repartition(4 * spark.sparkContext.defaultParallelism, "vec_id").withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))))
        each = each.withColumn("instance_id", F.col("vec_id") * copies + F.col("copy"))
        key = F.col("instance_id").cast("string")
        return each.select("instance_id", shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), F.col("vec_id").alias("source"), "copy", F.col("embedding").alias("features"), "label")
    if copies > 1:  # a small file is one split, and its copies are 128 times the work
        spread = out.repartition(4 * spark.sparkContext.defaultParallelism, "vec_id")
        out = spread.mapInArrow(_shifted(copies), "vec_id long, x array<double>, label double")
    key = F.col("vec_id").cast("string")
    return out.select(F.col("vec_id").alias("instance_id"), shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), F.col("x").alias("features"), "label")


def token_buckets(docs: DataFrame, key: str, text: str, buckets: int) -> DataFrame:
    """Long form: key, feature (bucket), value (count over the length of the count vector)."""
    words = F.filter(F.split(F.lower(F.col(text)), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    bucket = F.pmod(F.conv(F.substring(F.md5("word"), 1, 8), 16, 10).cast("long"), F.lit(buckets))
    counts = docs.select(key, F.explode(words).alias("word")).groupBy(key, bucket.alias("feature")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    # one row a document comes back, so its count vector never meets in one place
    norms = counts.groupBy(key).agg(F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("norm"))
    return counts.join(norms, key).select(key, "feature", (F.col("n") / F.col("norm")).alias("value"))


def document_quality(spark: SparkSession, sf_dir: str, target: str = "quality", buckets: int = 256, shards: int = 16, valid_pct: int = 20) -> DataFrame:
    """Hashed tokens of labelled documents as dense rows of `buckets` columns; label +1 or -1."""
    labels = read_table(spark, sf_dir, "labels", ["doc_id", target]).where(F.col(target).isNotNull())
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text"]).join(labels, "doc_id", "left_semi")
    long = token_buckets(docs, "doc_id", "text", buckets)
    packed = long.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("feature", "value"))).alias("m"))  # at most `buckets` entries
    dense = packed.join(labels, "doc_id").select("doc_id", F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda i: F.coalesce(F.try_element_at("m", i.cast("long")), F.lit(0.0))).alias("features"), (2.0 * F.col(target) - 1.0).alias("label"))
    key = F.col("doc_id").cast("string")
    return dense.select(F.col("doc_id").alias("instance_id"), shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), "features", "label")


def sparse_rows(docs: DataFrame, key: str, text: str, buckets: int) -> DataFrame:
    """key, places and features: the hashed tokens that a row has, ordered by place."""
    long = token_buckets(docs, key, text, buckets)
    packed = long.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("feature", "value"))).alias("own"))  # a row's tokens
    return packed.select(key, F.col("own.feature").cast("array<int>").alias("places"), F.col("own.value").alias("features"))


def sparse_documents(spark: SparkSession, sf_dir: str, target: str = "quality", buckets: int = 1 << 18, shards: int = 16, valid_pct: int = 20) -> DataFrame:
    """Labelled documents as sparse rows: label +1 or -1."""
    labels = read_table(spark, sf_dir, "labels", ["doc_id", target]).where(F.col(target).isNotNull())
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text"]).join(labels, "doc_id", "left_semi")
    key = F.col("doc_id").cast("string")
    own = sparse_rows(docs, "doc_id", "text", buckets).join(labels, "doc_id")
    return own.select(F.col("doc_id").alias("instance_id"), shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), "places", "features", (2.0 * F.col(target) - 1.0).alias("label"))


def sparse_pages(spark: SparkSession, sf_dir: str, buckets: int = 1 << 18, shards: int = 16, valid_pct: int = 20) -> DataFrame:
    """Pages as sparse rows of URL and HTML tokens; label: the page is longer than the median."""
    pages = read_table(spark, sf_dir, "pages", ["page_id", "url", "html"]).where("html is not null")
    size = F.length("html")
    mid = pages.agg(F.percentile(size, F.lit(0.5)).alias("mid"))
    labelled = pages.join(F.broadcast(mid)).select("page_id", F.concat_ws(" ", "url", "html").alias("text"), F.when(size > F.col("mid"), 1.0).otherwise(-1.0).alias("label"))
    key = F.col("page_id").cast("string")
    own = sparse_rows(labelled, "page_id", "text", buckets).join(labelled.select("page_id", "label"), "page_id")
    return own.select(F.col("page_id").alias("instance_id"), shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), "places", "features", "label")


def given_embeddings(spark: SparkSession, sf_dir: str, one: int | None = None, shards: int = 16, valid_pct: int = 20) -> DataFrame:
    """Embeddings with the label they came with, or +1 for label `one` and -1 for the rest."""
    own = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding", "label"])
    key = F.col("vec_id").cast("string")
    label = F.col("label").cast("double") if one is None else F.when(F.col("label") == one, 1.0).otherwise(-1.0)
    return own.select(F.col("vec_id").alias("instance_id"), shard_of(key, shards).alias("shard"), hash_split(key, valid_pct).alias("is_valid"), F.col("embedding").cast("array<double>").alias("features"), label.alias("label"))


def event_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared-loss instances from events: hour, one-hot type and the JSON counter k against value."""
    types = ["click", "purchase", "search", "signup", "view"]
    ev = read_table(spark, sf_dir, "events", ["event_id", "ts", "event_type", "value", "props"])
    k = F.from_json("props", "k int")["k"]
    return ev.select(F.col("event_id").alias("instance_id"), (F.hour("ts") / 24.0).alias("hour"), *[(F.col("event_type") == t).cast("double").alias(f"is_{t}") for t in types], k.cast("double").alias("k"), F.col("value").alias("label"))
