"""Copies whose features are made when they are read: the same rows on a fraction of the disk."""

import os

import numpy as np

from steepdraw.functions import columns as C
from steepdraw.functions import features as X
from steepdraw.functions.objectives import Linear, Mlp
from steepdraw.functions.steps import constant
from steepdraw.plans import local
from steepdraw.plans import trainers as T
from steepdraw.plans import workloads as W
from steepdraw.sources import tables as S


def _bytes(df):
    return sum(os.path.getsize(f.removeprefix("file://")) for f in df.inputFiles())


def _read(df):
    batches = df.select("instance_id", "shard", "is_valid", *T._inputs(df)).toArrow().combine_chunks().to_batches()
    return {i: (s, v, tuple(x), y) for b in batches for i, s, v, x, y in zip(*(b.column(c).to_pylist() for c in ("instance_id", "shard", "is_valid")), *(a.tolist() for a in T._arrow_matrix(b)), strict=True)}


def test_late_copies_are_the_same_rows_and_take_little_disk(spark, tiny):
    whole = X.planted_embeddings(spark, tiny, 10, copies=16)
    late = X.planted_embeddings(spark, tiny, 10, copies=16, late=True)
    assert _read(late) == _read(whole)
    data = S.sharded(W.load_task(spark, tiny, "augmented").data)
    assert data.count() == 128 * spark.read.parquet(f"{tiny}/embeddings.parquet").count()
    assert _bytes(data) < 64 * 8 * data.count() / 4  # less than a quarter of the features' bytes


def test_runs_over_late_copies_equal_those_over_whole_ones(spark, tiny):
    runs = []
    for late in (False, True):
        data = S.sharded(X.planted_embeddings(spark, tiny, 10, copies=4, late=late))
        obj, common = Mlp((64, 32, 10), "tanh"), {"batch": 32, "step_rule": constant(0.5), "seed": 3}
        flat = T.train("history", data, obj, steps=4, exec_mode="prefetch:2", eval_every=4, **common)
        step = T.train("history", data, obj, steps=2, exec_mode="per_step", eval_every=2, **common)
        staged = T.staged_history(data, obj, 2, shards=16, inner_steps=3, eval_every=3, measure_variance=True, **common)
        runs.append([(t["loss"], t["error"], t["var_ratio"]) for r in (flat, step, staged) for t in r.trace])
    assert np.allclose(*runs, rtol=1e-12, atol=0)


def test_heads_without_a_source_and_of_many_lengths():
    heads = [b"jitter:7:", b"jitter:1234567:127:", b"x" * 54 + b":", b""]
    want = [[C.py_uniform(h.decode()[:-1], j) if h else C.py_uniform(j) for j in range(120)] for h in heads]
    assert C.head_uniforms(heads, 120).tolist() == want
    x = np.ones((2, 4))
    got = X.shifted(x, [None, 5], np.array([0, 0]))
    made = np.array([[1 + (C.py_uniform(*k, j) - 0.5) * 0.02 for j in range(4)] for k in (("jitter", 0), ("jitter", 5, 0))])
    assert np.allclose(got, made / np.sqrt((made * made).sum(axis=1, keepdims=True)), rtol=1e-15)


def test_replaced_lengths_leave_no_table_behind_and_equal_lengths_none(spark, tmp_path, monkeypatch):
    rows = spark.range(300).selectExpr("id AS instance_id", "cast(id % 3 AS int) AS shard", "false AS is_valid", "array(cast(id AS double), 1.0D) AS features", "cast(1 AS double) AS label")
    data = S.checkpointed(rows, "instances")
    obj = Linear("logistic", 2)
    made = []
    monkeypatch.setattr(T, "checkpointed", lambda df, label: made.append(S.checkpointed(df, label)) or made[-1])
    flat = T._Stored(data, obj, np.zeros(2), "constant")
    assert not made and flat.current().selectExpr("sum(magnitude)").first()[0] == 300
    held = T._Stored(data, obj, np.zeros(2), "exact_scan", compact_rows=2)
    held.see(["1", "2"], [7.0, 8.0])
    now = {r.instance_id: r.magnitude for r in held.current().collect()}
    assert len(now) == 300 and (now["1"], now["2"]) == (7.0, 8.0) and now["0"] == 0.5
    first, second = (df.inputFiles()[0].removeprefix("file://") for df in made)
    assert not os.path.exists(os.path.dirname(first)) and os.path.exists(second)
    flat.compact_rows = 1
    flat.see(["1"], [2.0])
    assert flat.current().count() == 300 and data.count() == 300  # the caller's rows stay


def test_a_pass_in_blocks_equals_one_evaluation(monkeypatch):
    rng = np.random.default_rng(2)
    x, y, obj = rng.standard_normal((50, 6)), rng.integers(0, 3, 50).astype(float), Mlp((6, 5, 3))
    w = obj.start(1)
    losses, lengths, gradient = obj.evaluate(w, x, y)
    monkeypatch.setattr(local, "PASS_ROWS", 7)
    got = local.whole_pass(obj, w, x, y, True)
    for a, b in zip(got, (losses, lengths, gradient(np.full(50, 1 / 50))), strict=True):
        assert np.allclose(a, b, rtol=1e-12)
