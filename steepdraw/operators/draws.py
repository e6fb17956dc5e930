"""Weighted and uniform draws of rows, all from hash uniforms so that retries draw the same rows.

Every draw returns (step, draw_no, instance_id, prob, weight) with weight = 1 / (n * prob), fixed
at draw time.  Shards bound every sort: masses of shards go to the driver (one number a shard),
running sums are formed inside the shards that were hit, never over the whole table.
"""

from __future__ import annotations

import bisect
import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import block_uniforms, hash_uniform, py_uniform


def shard_masses(df: DataFrame, weight: str) -> DataFrame:
    """shard, rows and mass: the only state of a draw that grows with the shards."""
    return df.groupBy("shard").agg(F.count(F.lit(1)).alias("rows"), F.sum(weight).alias("mass"))


def _pick(masses: list[tuple[int, float]], u: float) -> tuple[int, float]:
    """Shard and the mass left inside it for a uniform number."""
    edges = list(itertools.accumulate(m for _, m in masses))
    at = min(bisect.bisect_right(edges, u * edges[-1]), len(edges) - 1)
    return masses[at][0], min(u * edges[-1] - (edges[at - 1] if at else 0.0), masses[at][1] * (1 - 1e-15))


def _finder(targets: dict):
    """Rows in order of (shard, instance_id) to the draws whose targets their running sums hold."""

    def run(batches):
        at, before, shard, last = 0, 0.0, None, None

        def found(rows: list[tuple]) -> pa.RecordBatch:
            step, draw_no, _ = (np.concatenate(c) for c in zip(*[r[0] for r in rows], strict=True))
            hit = pa.concat_batches([r[1] for r in rows])
            return pa.RecordBatch.from_arrays([pa.array(step), pa.array(draw_no), *hit.columns], names=["step", "draw_no", *hit.schema.names])

        def rest():
            """Targets that rounding left above the shard's running sum are of its last row with weight."""
            own = tuple(c[at:] for c in targets[shard]) if shard in targets else ()
            return [(own, pa.concat_batches([last] * len(own[0])))] if last and own and len(own[0]) else []

        for batch in batches:
            out = []
            shards, mass = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("shard", "_mass"))
            kept = batch.drop_columns(["shard", "_mass"])
            starts = np.flatnonzero(np.concatenate([[True], shards[1:] != shards[:-1]])) if len(shards) else []
            for a, z in zip(starts, [*starts[1:], len(shards)], strict=True):
                if shards[a] != shard:
                    out += rest()
                    at, before, shard, last = 0, 0.0, shards[a], None
                own = mass[a:z].copy()
                own[0] += before
                upto = np.cumsum(own)
                before = upto[-1]
                full = np.flatnonzero(mass[a:z])
                if len(full):
                    last = kept.slice(a + full[-1], 1)
                if shard not in targets:
                    continue
                end = np.searchsorted(targets[shard][2], before)  # targets below the running sum
                if end > at:
                    some = tuple(c[at:end] for c in targets[shard])
                    rows = a + np.searchsorted(upto, some[2], side="right")
                    out.append((some, kept.take(pa.array(rows))))
                    at = end
            if out:
                yield found(out)
        out = rest()
        if out:
            yield found(out)

    return run


def _locate(df: DataFrame, weight: str, plan: list[tuple] | tuple, mass: Column | None = None) -> DataFrame:
    """step, draw_no, instance_id and weight of the rows whose interval of the shard's running sums (of mass, or of the weight) holds a target.

    One sort and one pass: the targets of a shard are in order too, so each costs one search in the
    batch that holds it, not a comparison with every row.
    """
    step, draw_no, shard, target = (np.array(c) for c in (zip(*plan, strict=True) if isinstance(plan, list) and plan else plan or [[]] * 4))
    order = np.lexsort((draw_no, step, target, shard))
    names, starts = np.unique(shard[order], return_index=True)
    parts = [np.split(c, starts[1:]) for c in (step[order].astype(np.int64), draw_no[order].astype(np.int32), target[order].astype(float))]
    targets = dict(zip(names.tolist(), zip(*parts, strict=True), strict=False))
    own = F.coalesce(F.col(weight) if mass is None else mass, F.lit(0.0)).cast("double")
    rows = df.where(F.col("shard").isin(list(targets))).select("instance_id", "shard", weight, own.alias("_mass"))
    order = rows.repartition(2 * max(1, len(targets)), "shard").sortWithinPartitions("shard", "instance_id")
    kinds = dict(rows.dtypes)
    return order.mapInArrow(_finder(targets), f"step long, draw_no int, instance_id {kinds['instance_id']}, {weight} {kinds[weight]}")


def uniform_draw(df: DataFrame, b: int, seed: int, step: int) -> DataFrame:
    """b rows with replacement: a shard by its count, then a rank inside it."""
    return two_level_draw(df.withColumn("_one", F.lit(1.0)), "_one", b, seed, step)


def block_draw(df: DataFrame, weight: str, b: int, seed: int, steps: range | list[int], masses: list | None = None) -> DataFrame:
    """b draws for each of several steps in one job, all in proportion to `weight`.

    Shards are picked on the driver from one mass each, rows by running sums inside hit shards.
    """
    if masses is None:
        masses = [tuple(r) for r in shard_masses(df, weight).orderBy("shard").collect()]  # one row a shard
    n, total = sum(r[1] for r in masses), sum(r[2] for r in masses)
    if not total:
        raise ValueError("all weights are zero")
    spread = [(s, m) for s, _, m in masses if m > 0]
    steps = np.array(steps, np.int64)
    whole = len(steps) and (np.diff(steps) == 1).all()
    u = (block_uniforms(seed, int(steps[0]), len(steps), b) if whole else np.array([[py_uniform(seed, t, j) for j in range(b)] for t in steps.tolist()])).ravel()
    edges = np.array(list(itertools.accumulate(m for _, m in spread)))
    at = np.minimum(np.searchsorted(edges, u * edges[-1], side="right"), len(edges) - 1)
    own, of = np.array([m for _, m in spread]), np.array([s for s, _ in spread])
    target = np.minimum(u * edges[-1] - np.where(at > 0, edges[at - 1], 0.0), own[at] * (1 - 1e-15))
    plan = np.repeat(steps, b), np.tile(np.arange(b), len(steps)), of[at], target
    prob = F.col(weight) / F.lit(total)
    return _locate(df, weight, plan).select("step", "draw_no", "instance_id", prob.alias("prob"), (1.0 / (n * prob)).alias("weight"))


def two_level_draw(df: DataFrame, weight: str, b: int, seed: int, step: int, masses: list | None = None) -> DataFrame:
    """b draws of one step in proportion to `weight`."""
    return block_draw(df, weight, b, seed, [step], masses)


def mixture_draw(df: DataFrame, weight: str, beta: float, b: int, seed: int, step: int) -> DataFrame:
    """b draws from (1 - beta) * weight share + beta / n, without forming that column."""
    masses = [tuple(r) for r in shard_masses(df, weight).orderBy("shard").collect()]
    n, total = sum(r[1] for r in masses), sum(r[2] for r in masses)
    if not total:
        beta = 1.0
    flat, steep = [(s, float(c)) for s, c, _ in masses], [(s, m) for s, _, m in masses if m > 0]
    plan: tuple[list, list] = ([], [])
    for j in range(b):
        u = py_uniform(seed, step, j)
        if u < beta:
            plan[0].append((step, j, *_pick(flat, u / beta)))
        else:
            plan[1].append((step, j, *_pick(steep, (u - beta) / (1 - beta))))
    both = _locate(df, weight, plan[0], F.lit(1.0)).unionByName(_locate(df, weight, plan[1]))
    prob = (1 - beta) * F.col(weight) / F.lit(total or 1.0) + F.lit(beta / n)
    return both.select("step", "draw_no", "instance_id", prob.alias("prob"), (1.0 / (n * prob)).alias("weight"))


MOST_RATE = 500.0  # exp(-rate) keeps all its digits


def poisson_draw(df: DataFrame, prob: str, b: int, n: int, seed: int, step: int) -> DataFrame:
    """One scan, no prefix sums: each row takes Poisson(b * prob) copies by its own uniform.

    Rows whose uniform already lies below the probability of no copy leave after one comparison;
    the others walk up the distribution until they pass it.  A rate above MOST_RATE is the sum of
    equal parts, each with a uniform of its own.
    """
    u, rate = hash_uniform(seed, step, F.col("instance_id")), F.lit(float(b)) * F.col(prob)
    some = df.select("instance_id", prob).where((rate > MOST_RATE) | (u >= F.exp(-rate)))

    def walk(x):
        """Copies of (u, rate); a mean of 500 is passed by 12 deviations and 30 with certainty."""
        start = F.struct(F.exp(-x["rate"]).alias("term"), F.exp(-x["rate"]).alias("below"), F.lit(0).alias("copies"))

        def further(acc, k):
            term = acc["term"] * x["rate"] / k
            return F.struct(term.alias("term"), (acc["below"] + term).alias("below"), (acc["copies"] + F.when(x["u"] >= acc["below"], 1).otherwise(0)).alias("copies"))

        reach = (x["rate"] + 12 * F.sqrt(x["rate"]) + 30).cast("int")
        return F.aggregate(F.sequence(F.lit(1), reach), start, further)["copies"]

    parts = F.greatest(F.lit(1), F.ceil(rate / MOST_RATE).cast("int"))
    draw = lambda k: F.struct(F.when(k == 1, u).otherwise(hash_uniform(seed, step, F.col("instance_id"), k)).alias("u"), (rate / parts).alias("rate"))
    copies = F.aggregate(F.transform(F.transform(F.sequence(F.lit(1), parts), draw), walk), F.lit(0), lambda total, c: total + c)
    drawn = some.select("instance_id", prob, copies.alias("copies")).where("copies > 0")
    return drawn.select(F.lit(step).alias("step"), "copies", "instance_id", F.col(prob).alias("prob"), (1.0 / (n * F.col(prob))).alias("weight"))


def subset_without_replacement(df: DataFrame, m: int, seed: int, stage: int) -> DataFrame:
    """The m rows with the smallest hashes; top-k in each task, then among tasks."""
    return df.withColumn("u", hash_uniform(seed, stage, F.col("instance_id"))).orderBy("u", "instance_id").limit(m)


def subset_by_threshold(df: DataFrame, m: int, n: int, seed: int, stage: int) -> DataFrame:
    """Large m: a plain filter on the hash keeps a superset, which is then trimmed exactly."""
    bound = min(1.0, m / n + 6 * math.sqrt(m) / n)
    few = df.withColumn("u", hash_uniform(seed, stage, F.col("instance_id"))).where(F.col("u") < bound)
    return few.orderBy("u", "instance_id").limit(m)


def exponential_key_topk(df: DataFrame, weight: str, b: int, seed: int) -> DataFrame:
    """Weighted sample without replacement, for previews only: 1/(n p) doesn't undo its bias."""
    return df.where(F.col(weight) > 0).withColumn("key", -F.log(hash_uniform(seed, F.col("instance_id"))) / F.col(weight)).orderBy("key").limit(b)


def global_cdf_draw(df: DataFrame, prob: str, b: int, seed: int, step: int) -> DataFrame:
    """Running sum over all rows, shard after shard: the plain definition, of every row.

    Sums of whole shards carry the running sums from shard to shard, so no task holds the table.
    """
    spark: SparkSession = df.sparkSession
    masses = [tuple(r) for r in shard_masses(df, prob).orderBy("shard").collect()]  # one row a shard
    total = sum(r[1] for r in masses)
    before = list(itertools.accumulate((r[2] for r in masses), initial=0.0))
    starts = spark.createDataFrame([(r[0], m) for r, m in zip(masses, before, strict=False)], "_shard int, _before double")
    own = Window.partitionBy("shard").orderBy("instance_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    every = df.withColumn("upto", F.sum(prob).over(own)).join(F.broadcast(starts), F.col("shard") == F.col("_shard")).withColumn("upto", F.col("upto") + F.col("_before"))
    targets = spark.createDataFrame([(step, j, py_uniform(seed, step, j) * before[-1]) for j in range(b)], "step long, draw_no int, u double")
    hit = (F.col("u") < F.col("upto")) & (F.col("u") >= F.col("upto") - F.col(prob))
    return every.join(F.broadcast(targets), hit).select("step", "draw_no", "instance_id", F.col(prob).alias("prob"), (1.0 / (total * F.col(prob))).alias("weight"))
