"""Theory and trainers against brute force, closed forms and each other."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from steepdraw.functions import columns as C
from steepdraw.functions import features as X
from steepdraw.functions.objectives import Linear, Mlp, Pca, Penalty, outer_lengths
from steepdraw.functions.steps import constant, inverse_sqrt, momentum, per_coordinate
from steepdraw.operators import draws as D
from steepdraw.operators import history as H
from steepdraw.operators import measures as M
from steepdraw.plans import local, theory
from steepdraw.plans import trainers as T

RNG = np.random.default_rng(3)


def rows(n=60, d=4):
    x = RNG.standard_normal((n, d)) * np.exp(RNG.standard_normal((n, 1)))
    y = np.where(x @ np.arange(1, d + 1) + RNG.standard_normal(n) > 0, 1.0, -1.0)
    return x, y


OBJECTIVES = [(Linear("squared", 4), None), (Linear("hinge", 4), None), (Linear("logistic", 4), None), (Mlp((4, 3)), 3), (Mlp((4, 5, 3), "tanh"), 3), (Mlp((4, 5, 4, 3), "sigmoid", include_bias=True), 3), (Mlp((4, 6, 3), "relu"), 3), (Pca(4, 2), 0)]


@pytest.mark.parametrize("obj,classes", OBJECTIVES)
def test_gradients_match_finite_differences(obj, classes):
    x, y = rows(8)
    if classes:
        y = RNG.integers(0, classes, len(y)).astype(float)
    w = obj.start(1) + 0.1 * RNG.standard_normal(len(obj.start(1)))
    weight = RNG.uniform(0.5, 2, len(x))
    g = obj.evaluate(w, x, y)[2](weight)
    for j in range(len(w)):
        e = np.zeros(len(w))
        e[j] = 1e-6
        up, down = (float(weight @ obj.evaluate(w + s * e, x, y)[0]) for s in (1, -1))
        assert g[j] == pytest.approx((up - down) / 2e-6, rel=2e-4, abs=2e-5)


@pytest.mark.parametrize("obj,classes", OBJECTIVES)
def test_lengths_from_row_norms_equal_brute_force(obj, classes):
    x, y = rows(20)
    if classes:
        y = RNG.integers(0, classes, len(y)).astype(float)
    w = obj.start(2) + 0.1
    lengths = obj.evaluate(w, x, y)[1]
    naive = outer_lengths(obj, w, x, y, weights_only=isinstance(obj, Mlp) and not obj.include_bias)
    assert np.allclose(lengths, naive, atol=1e-10)


def test_stored_length_ignores_the_row_weight():
    x, y = rows(50)
    obj = Linear("logistic", 4)
    s = local.run_steps(obj, x, y, np.zeros(4), method="history", steps=1, batch=8, rule=constant(0.1), seed=1, magnitude=RNG.uniform(0.1, 5, 50))
    seen = s.visits > 0
    assert np.allclose(s.magnitude[seen], obj.evaluate(np.zeros(4), x, y)[1][seen])


def test_best_probabilities_minimise_variance():
    x, y = rows(200)
    lengths, g = (lambda r: (r[1], r[2](np.full(200, 1 / 200))))(Linear("logistic", 4).evaluate(np.full(4, 0.2), x, y))
    best = local.variance(lengths, lengths / lengths.sum(), g)
    assert best == pytest.approx(lengths.mean() ** 2 - g @ g)
    for _ in range(100):
        p = RNG.dirichlet(np.ones(200))
        assert best <= local.variance(lengths, p, g) + 1e-9
    assert best <= local.variance(lengths, np.full(200, 1 / 200), g)


def test_weighted_gradient_is_unbiased_for_any_probabilities():
    x, y = rows(40)
    obj = Linear("logistic", 4)
    per_row = np.array([obj.evaluate(np.ones(4), x[i : i + 1], y[i : i + 1])[2](np.ones(1)) for i in range(40)])
    for p in (RNG.dirichlet(np.ones(40)), local.probabilities(RNG.uniform(0, 1, 40), 0.3)):
        assert np.allclose((p[:, None] * per_row / (40 * p[:, None])).sum(axis=0), per_row.mean(axis=0))


def test_floor_starvation_and_zero_total():
    p = local.probabilities(np.array([0.0, 1.0, 3.0]), 0.3)
    assert p.sum() == pytest.approx(1) and (3 * p).min() >= 0.3 - 1e-12
    assert np.allclose(local.probabilities(np.zeros(4), 0.2), 0.25)
    assert local.probabilities(np.array([0.0, 1.0]), 0.0)[0] == 0
    with pytest.raises(ValueError):
        local.run_steps(Linear("logistic", 2), np.ones((2, 2)), np.ones(2), np.zeros(2), method="history", steps=1, rule=constant(0.1), beta=0.0)


def test_full_floor_equals_uniform():
    x, y = rows(64)
    a = local.run_steps(Linear("logistic", 4), x, y, np.zeros(4), method="history", beta=1.0, steps=20, batch=4, rule=constant(0.2), seed=5)
    b = local.run_steps(Linear("logistic", 4), x, y, np.zeros(4), method="uniform", steps=20, batch=4, rule=constant(0.2), seed=5)
    assert np.allclose(a.w, b.w)


def test_draw_law():
    p = local.probabilities(RNG.uniform(0, 1, 20) ** 4, 0.1)
    u = np.array([C.py_uniform(1, 2, j) for j in range(20_000)])
    got = np.bincount(local.draw(p, u), minlength=20)
    chi = (((got - 20_000 * p) ** 2) / (20_000 * p)).sum()
    assert chi < 45  # 19 degrees of freedom


def test_variance_falls_and_history_saves_error():
    x = RNG.standard_normal((2000, 3))
    y = np.where(x[:, 0] - 0.1 * x[:, 1] > 0, 1.0, -1.0)
    obj = Linear("logistic", 3)
    final = {}
    for method in ("uniform", "history"):
        errors, ratios = [], []
        for seed in range(21, 26):
            s = local.run_steps(obj, x, y, np.zeros(3), method=method, steps=1500, batch=4, rule=constant(5.0), seed=seed, eval_every=300, measure_variance=True, magnitude=obj.evaluate(np.zeros(3), x, y)[1])
            errors.append(np.mean([t["error"] for t in s.trace[-3:]]))
            ratios.append([t["var_ratio"] for t in s.trace])
        final[method] = np.mean(errors)
        if method == "history":
            mean = np.mean(ratios, axis=0)
            assert mean[-1] < 0.5 and mean[-1] < mean[0] + 0.05
    assert final["history"] < final["uniform"]


def test_equal_rows_have_nothing_to_gain():
    x, y = np.ones((50, 2)), np.ones(50)
    s = local.run_steps(Linear("logistic", 2), x, y, np.zeros(2), method="exact", steps=3, batch=4, rule=constant(0.1), seed=1, eval_every=1, measure_variance=True)
    assert all(t["var_ratio"] == 1.0 for t in s.trace)


def test_greedy_rule_visits_in_proportion_to_gain():
    # intervals are whole numbers, so the law needs many rows
    x = np.linspace(0.5, 2, 200)[:, None]
    s = local.run_steps(Linear("logistic", 1), x, np.ones(200), np.zeros(1), method="infogain", steps=20_000, batch=1, rule=constant(0.0), seed=1)
    share = x[:, 0] / x.sum()
    assert np.allclose(s.visits / s.visits.sum(), share, rtol=0.1)


def test_uncertainty_forms_differ():
    p = np.linspace(0.01, 0.5, 50)
    entropy, expected = -(p * np.log(p) + (1 - p) * np.log(1 - p)), 2 * p * (1 - p)
    assert (np.diff(entropy) > 0).all() and (np.diff(expected) > 0).all()
    assert entropy[-1] / expected[-1] == pytest.approx(2 * math.log(2))
    assert entropy[0] / expected[0] > 2


def test_strong_pull_freezes_a_stage_and_rules_move():
    x, y = rows(64)
    start = np.full(4, 0.3)
    s = local.run_steps(Linear("logistic", 4), x, y, start, method="history", steps=50, batch=8, rule=constant(1e-4), seed=2, anchor=start, gamma=1e4)
    assert np.abs(s.w - start).max() < 1e-3
    for rule in (constant(0.1), inverse_sqrt(0.1), momentum(0.1), per_coordinate(0.1)):
        assert np.linalg.norm(local.run_steps(Linear("squared", 4), x, y, start, method="uniform", steps=5, batch=8, rule=rule).w - start) > 0


def test_snapshot_and_l1():
    x, y = rows(100)
    obj = Linear("logistic", 4, Penalty("l1", 0.5))
    s = local.run_steps(obj, x, y, np.zeros(4), method="snapshot", steps=200, batch=8, rule=constant(0.05), seed=1, snapshot_every=20, prox=True)
    assert np.count_nonzero(s.w) < 4


def test_expression_losses_equal_numpy(spark):
    x, y = rows(30)
    w = [0.3, -0.2, 0.1, 0.5]
    df = spark.createDataFrame([(*map(float, a), float(b)) for a, b in zip(x, y, strict=True)], "x1 double, x2 double, x3 double, x4 double, label double")
    for kind in ("squared", "hinge", "logistic"):
        got = M.scored(df, ["x1", "x2", "x3", "x4"], w, kind).agg(F.avg("loss").alias("l"), F.sum("len").alias("s")).first()
        losses, lengths, _ = Linear(kind, 4).evaluate(np.array(w), x, y)
        assert got.l == pytest.approx(losses.mean()) and got.s == pytest.approx(lengths.sum())


def _instances(spark, tiny, m=120):
    own = X.as_instances(X.net_price(spark, tiny), theory.FEATURES, shards=4, valid_pct=10)
    return own.orderBy(C.hash_uniform("t", F.col("instance_id"))).limit(m)


def test_two_level_draw_is_the_weighted_law(spark):
    df = spark.createDataFrame([(i, i % 3, float(i % 5)) for i in range(50)], "instance_id long, shard int, m double")
    got = D.two_level_draw(df, "m", 2000, 4, 1).groupBy("instance_id").count().collect()
    share = {r.instance_id: r["count"] / 2000 for r in got}
    assert all(share.get(i, 0) == 0 for i in range(0, 50, 5))
    assert all(abs(share.get(i, 0) - (i % 5) / 100) < 0.02 for i in range(50))


def test_draws_do_not_depend_on_partitions(spark):
    df = spark.createDataFrame([(i, i % 3, float(i % 5)) for i in range(50)], "instance_id long, shard int, m double")
    a = D.mixture_draw(df, "m", 0.3, 64, 4, 1).orderBy("draw_no").collect()
    b = D.mixture_draw(df.repartition(7), "m", 0.3, 64, 4, 1).orderBy("draw_no").collect()
    assert [(r.draw_no, r.instance_id) for r in a] == [(r.draw_no, r.instance_id) for r in b] and len(a) == 64
    assert all(r.weight <= 1 / 0.3 + 1e-9 for r in a)


def test_modes_agree_on_one_prefetched_step(spark, tiny):
    data = _instances(spark, tiny)
    obj = Linear("logistic", 5)
    a = T.train("history", data, obj, steps=2, batch=8, step_rule=constant(0.5), seed=3, exec_mode="per_step", init="exact_scan")
    b = T.train("history", data, obj, steps=2, batch=8, step_rule=constant(0.5), seed=3, exec_mode="prefetch:1", init="exact_scan")
    assert np.allclose(a.model, b.model)


def test_staged_training_with_carried_history(spark, tiny):
    data = _instances(spark, tiny, 400)
    r = T.staged_history(data, Linear("logistic", 5), 3, shards=4, batch=8, inner_steps=20, step_rule=constant(0.5), seed=2, eval_every=10)
    assert len(r.trace) == 6 and r.history.count() > 20
    assert r.trace[-1]["loss"] < math.log(2)
    assert r.history.groupBy("instance_id").count().where("count > 1").count() == 0


def test_history_compaction_and_probabilities(spark):
    h = spark.createDataFrame([("a", 0, 1.0, 1), ("b", 0, 0.0, 1)], "instance_id string, shard int, magnitude double, last_step long")
    d = spark.createDataFrame([("a", 0, 5.0, 3), ("a", 0, 2.0, 2)], "instance_id string, shard int, magnitude double, last_step long")
    assert {r.instance_id: r.magnitude for r in H.compact(h, d).collect()} == {"a": 5.0, "b": 0.0}
    assert sum(r.prob for r in H.probabilities(h, 0.2).collect()) == pytest.approx(1)


def test_hash_uniform_value(spark):
    assert int(C.py_uniform(7, 1, 3) * C.SPAN) == 272049632541310
    assert spark.range(1).select(C.hash_uniform(7, 1, 3).alias("u")).first().u == C.py_uniform(7, 1, 3)


def test_augmented_copies_are_spread_over_tasks_and_follow_their_definition(spark, tiny):
    out = X.planted_embeddings(spark, tiny, 10, copies=8)
    assert out.rdd.getNumPartitions() > 1  # the table is one small file
    given = {r.vec_id: np.array(r.embedding, dtype=float) for r in spark.read.parquet(f"{tiny}/embeddings.parquet").collect()}
    found = out.collect()
    assert sorted(r.instance_id for r in found) == sorted(8 * v + c for v in given for c in range(8))
    for r in found[::97]:
        v, c = divmod(r.instance_id, 8)
        x = np.array([e + (C.py_uniform("jitter", v, c, i) - 0.5) * 0.02 for i, e in enumerate(given[v])])
        x = np.roll(x, c % 4)
        assert np.allclose(r.features, x / np.sqrt(x @ x), rtol=0, atol=1e-14)


def test_greatest_values_are_those_of_a_full_sort(monkeypatch):
    values = [RNG.integers(0, 5, 200).astype(float), RNG.standard_normal(200), np.zeros(50), np.array([np.nan, 2.0, np.nan, 3.0, 2.0]), np.array([-np.inf, np.inf, 0.0])]
    for v in values:
        for b in (1, 2, 3, 16, 500):
            assert local.greatest(v, b).tolist() == np.lexsort((np.arange(len(v)), -v))[:b].tolist()
    x, y = rows(60)
    whole = lambda *a, **k: pytest.fail("all rows were sorted")
    monkeypatch.setattr(local.np, "lexsort", whole)
    local.run_steps(Linear("logistic", 4), x, y, np.zeros(4), method="infogain", steps=2, batch=5, rule=constant(0.1))


def test_block_draws_search_running_sums_and_join_no_row_with_all_targets(spark):
    mass = [None if i % 11 == 0 else 0.0 if i % 7 == 0 else float(i % 5) + 0.1 for i in range(400)]
    df = spark.createDataFrame([(f"{i:04d}", i % 3, m) for i, m in enumerate(mass)], "instance_id string, shard int, m double")
    out = D.block_draw(df, "m", 50, 4, range(8, 12))
    assert "Join" not in out._jdf.queryExecution().optimizedPlan().toString()
    sums = [sum(m or 0.0 for m in mass[s::3]) for s in range(3)]
    got = {(r.step, r.draw_no): r for r in out.collect()}
    assert len(got) == 200
    for (t, j), r in got.items():
        left = C.py_uniform(4, t, j) * sum(sums)
        shard = int(np.searchsorted(np.cumsum(sums), left, side="right"))
        inside = np.cumsum([m or 0.0 for m in mass[shard::3]])
        want = shard + 3 * int(np.searchsorted(inside, left - sum(sums[:shard]), side="right"))
        assert int(r.instance_id) == want and r.prob == pytest.approx(mass[want] / sum(sums))


def test_block_uniforms_equal_single_ones():
    for seed, first, steps, count in ((11, 1, 12, 130), (7, 999_995, 9, 3), ("x" * 60, 5, 3, 12)):
        want = [[C.py_uniform(seed, t, j) for j in range(count)] for t in range(first, first + steps)]
        assert C.block_uniforms(seed, first, steps, count).tolist() == want


def test_many_rows_are_drawn_and_changed_without_a_pass_over_all(monkeypatch):
    m = RNG.uniform(0, 1, 70_001) ** 3
    tree, u = local.Mixture(m, 0.2), np.append(RNG.uniform(0, 1, 20_000), [0.0, 1.0])
    for _ in range(2):
        p = local.probabilities(tree.magnitude, 0.2)
        drawn, prob = tree.draw(u)
        assert (drawn == local.draw(p, u)).all() and np.allclose(prob, p[drawn], rtol=1e-12)
        own = np.append(RNG.integers(0, 70_001, 3000), [70_000, 5, 5])
        tree.put(own, RNG.uniform(0, 9, len(own)))
        tree.refresh()
    x, y = rows(70_001)
    run = lambda: local.run_steps(Linear("logistic", 4), x, y, np.zeros(4), method="history", steps=40, batch=16, redraw_every=8, rule=constant(0.5), seed=3, eval_every=40, measure_variance=False)
    monkeypatch.setattr(local, "TREE_ROWS", 1 << 30)
    whole = run()
    monkeypatch.setattr(local, "TREE_ROWS", 1 << 15)
    monkeypatch.setattr(local, "probabilities", lambda *a: pytest.fail("all rows were summed again"))
    few = run()
    assert np.allclose(whole.w, few.w) and (whole.visits == few.visits).all() and (whole.last_step == few.last_step).all() and np.allclose(whole.magnitude, few.magnitude)


def test_a_stage_holds_arrays_and_gives_what_the_plain_loop_gives(spark, tiny):
    data = _instances(spark, tiny, 300)
    w, trace, rows, status = T.stage_run(data, Linear("logistic", 5), np.zeros(5), method="history", steps=20, batch=8, rule=constant(0.5), seed=3, eval_every=10, measure_variance=True)
    pdf = data.toPandas().sort_values("instance_id").reset_index(drop=True)
    own, held = pdf[~pdf["is_valid"]].reset_index(drop=True), pdf[pdf["is_valid"]]
    s = local.run_steps(Linear("logistic", 5), *T._matrix(own), np.zeros(5), method="history", steps=20, batch=8, rule=constant(0.5), seed=3, eval_every=10, measure_variance=True, x_valid=T._matrix(held)[0], y_valid=T._matrix(held)[1])
    assert np.array_equal(w, s.w) and [t["error"] for t in trace] == [t["error"] for t in s.trace]
    assert {r.instance_id: (r.magnitude, r.visits) for r in rows.collect()} == {i: (m, v) for i, m, v in zip(own["instance_id"], s.magnitude, s.visits, strict=True) if v}
    assert T.stage_run(data, Linear("logistic", 5), np.zeros(5), method="history", steps=20, batch=8, rule=constant(0.5), seed=3, keep_rows=False)[2] is None


def test_held_out_rows_of_a_subset_stage_are_judged_in_their_own_tasks(spark, tiny, monkeypatch):
    data = _instances(spark, tiny, 600)
    given, kept = [], T.stage_run
    monkeypatch.setattr(T, "stage_run", lambda own, *a, **k: given.append(own.where("is_valid").count()) or kept(own, *a, **k))
    r = T.staged_history(data, Linear("logistic", 5), 2, subset_rows=100, batch=8, inner_steps=20, step_rule=constant(0.5), seed=2, eval_every=1 << 30)
    held = data.where("is_valid").toPandas()
    assert given == [0, 0] and len(held) > 30
    assert r.trace[-1]["error"] == Linear("logistic", 5).wrong(r.model, *T._matrix(held)).mean()
