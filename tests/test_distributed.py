"""Distributed modes, sparse rows, stages over all shards and Poisson counts against plain NumPy."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from steepdraw.functions.objectives import Linear, SparseRows, outer_lengths
from steepdraw.functions.steps import constant
from steepdraw.operators import draws as D
from steepdraw.plans import local, workloads
from steepdraw.plans import trainers as T
from steepdraw.sources.tables import sharded


@pytest.fixture(scope="module")
def task(spark, tiny):
    w = workloads.load_task(spark, tiny, "net_price")
    return w, sharded(w.data)


def test_sparse_rows_equal_dense_ones():
    rng = np.random.default_rng(1)
    dense = rng.standard_normal((40, 30)) * (rng.uniform(size=(40, 30)) < 0.1)
    places = [np.flatnonzero(r).tolist() for r in dense]
    sparse = SparseRows.of(places, [dense[i, p].tolist() for i, p in enumerate(places)])
    y, w = np.sign(rng.standard_normal(40)), rng.standard_normal(30)
    obj, some, weight = Linear("logistic", 30), np.array([3, 3, 0, 39, 17]), rng.uniform(size=40)
    for a, b in ((obj.evaluate(w, dense, y), obj.evaluate(w, sparse, y)), (obj.evaluate(w, dense[some], y[some]), obj.evaluate(w, sparse[some], y[some]))):
        np.testing.assert_allclose(a[0], b[0])
        np.testing.assert_allclose(a[1], b[1])
    np.testing.assert_allclose(obj.evaluate(w, dense, y)[2](weight), obj.evaluate(w, sparse, y)[2](weight))
    np.testing.assert_allclose(obj.evaluate(w, sparse, y)[1], outer_lengths(obj, w, dense, y))
    run = [local.run_steps(obj, x, y, np.zeros(30), method="history", steps=20, batch=4, rule=constant(0.3), eval_every=20).w for x in (dense, sparse)]
    np.testing.assert_allclose(*run)


def test_a_look_equals_the_plain_measures(task):
    w, data = task
    run = T.train("history", data, w.objective, steps=30, batch=16, step_rule=constant(0.5), seed=3, exec_mode="prefetch:10", eval_every=30)
    pdf = data.withColumn("instance_id", F.col("instance_id").cast("string")).join(run.history.select("instance_id", "magnitude"), "instance_id").toPandas()
    own, held = pdf[~pdf["is_valid"]], pdf[pdf["is_valid"]]
    x, y = T._matrix(own)
    losses, lengths, gradient = w.objective.evaluate(run.model, x, y)
    n, g = len(own), gradient(np.full(len(own), 1 / len(own)))
    p = local.probabilities(own["magnitude"].to_numpy(), 0.2)
    look = run.trace[-1]
    assert look["loss"] == pytest.approx(losses.mean()) and look["error"] == pytest.approx(w.objective.wrong(run.model, *T._matrix(held)).mean())
    assert look["var_ratio"] == pytest.approx(local.variance(lengths, p, g) / local.variance(lengths, np.full(n, 1 / n), g))
    assert look["max_weight"] > 1 and look["elapsed_s"] > 0
    assert run.history.count() == data.count()


def test_stages_visit_every_shard_as_often_as_asked(task):
    w, data = task
    sizes = {r.shard: r["count"] for r in data.where("not is_valid").groupBy("shard").count().collect()}
    seen = []
    r = T.staged_history(data, w.objective, 16, shards=16, visits=16, batch=128, step_rule=constant(0.5), seed=1, eval_every=1 << 30, measure_variance=True, history="exact_scan", after_stage=lambda t, step, *_: seen.append(step))
    assert r.extra["subset_rows"] == [sizes[t] for t in range(16)]
    assert np.diff([0, *seen]).tolist() == [16 * sizes[t] // 128 for t in range(16)]
    assert [t["stage"] for t in r.trace] == list(range(16)) and r.trace[-1]["var_ratio"] < r.trace[0]["var_ratio"]


def test_staged_steps_run_distributed(task):
    w, data = task
    r = T.staged_history(data, w.objective, 2, shards=16, inner_steps=2, batch=16, exec_mode="per_step", init="exact_scan", step_rule=constant(0.5), seed=1, eval_every=2)
    assert [t["step"] for t in r.trace] == [2, 4] and len(r.extra["sent"]) == 4
    assert all(s["up"] == 8 * 5 * s["tasks"] and s["lengths"] > 0 for s in r.extra["sent"])


def test_poisson_counts_have_the_right_mean_at_any_rate(spark):
    df = spark.range(3000).select(F.col("id").cast("string").alias("instance_id"), F.when(F.col("id") == 0, 0.9).otherwise(F.when(F.col("id") < 100, 0.0005).otherwise(0.05 / 2900)).alias("p"))
    got = {r.instance_id: r.copies for r in D.poisson_draw(df, "p", 100_000, 3000, 5, 1).collect()}
    assert abs(got["0"] - 90_000) < 6 * 300  # far beyond one exponential's digits
    mid = [got.get(str(i), 0) for i in range(1, 100)]
    assert abs(np.mean(mid) - 50) < 4 and 25 < np.var(mid) < 90
    rest = [got.get(str(i), 0) for i in range(100, 3000)]
    assert np.mean(rest) == pytest.approx(100_000 * 0.05 / 2900, rel=0.1)


def test_two_levels_and_the_whole_running_sum_name_the_same_rows(spark):
    df = spark.range(500).select(F.col("id").cast("string").alias("instance_id"), F.pmod("id", F.lit(7)).cast("int").alias("shard"), (1.0 + F.pmod("id", F.lit(13))).alias("m"))
    a = {r.draw_no: r.instance_id for r in D.two_level_draw(df, "m", 64, 5, 2).collect()}
    b = {r.draw_no: r.instance_id for r in D.global_cdf_draw(df, "m", 64, 5, 2).collect()}
    assert a == b and len(a) == 64


@pytest.mark.parametrize("name", ["event_value", "given_ten", "kernel_given_3", "no_signal", "page_sparse"])
def test_workloads_train(spark, tiny, name):
    w = workloads.load_task(spark, tiny, name)
    t = workloads.run_methods(spark, w, 32, methods=("uniform", "staged"), eval_every=32).collect()
    assert {r.method for r in t} == {"uniform", "staged"} and all(np.isfinite(r.loss) for r in t)
