"""The experiment workloads on the given tables, and the traces and comparisons drawn from them.

net_price        tabular, near-linear, skewed lengths (logistic, hinge or squared loss)
kernel           planted two-class embeddings through random Fourier features, hinge + l2
kernel_given_c   the same features, given label c against the rest
doc_quality      hashed tokens of labelled documents, 256 dense columns, logistic + l1 (also doc_toxic)
doc_sparse       the same tokens in 2^18 sparse columns, proximal l1 (also toxic_sparse, page_sparse)
page_url         hashed URL tokens, label: page longer than the median; logistic + l1
planted_ten      ten planted classes of embeddings, dense network; given_ten: the label they came with
augmented        the same with 128 shifted, jittered copies; batch 512
event_value      heavy-tailed values of events, squared loss
pca              embeddings without labels
identical        copies of one row: nothing to gain, both variances are zero
no_signal        a label that the features know nothing of: lengths nearly equal

Every workload trains on all its rows.  Uniform draws and stored lengths over a whole table run in
blocks of prefetched steps; the staged method, and every method that needs its rows in one task,
goes from shard to shard, so a task holds one shard whatever the table's size.
"""

from __future__ import annotations

from dataclasses import dataclass

import time

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import features as X
from ..functions.objectives import Linear, Mlp, Pca, Penalty, fourier_features
from ..functions.steps import constant
from ..operators import draws as D
from ..sources.tables import checkpointed, read_table, sharded
from . import trainers as T


@dataclass
class Workload:
    name: str
    data: DataFrame
    objective: object
    eta: float
    batch: int = 128


def _fourier(data: DataFrame, dim: int = 128, width: float = 1.0, seed: int = 5) -> DataFrame:
    def run(batches):
        for pdf in batches:
            if len(pdf):
                x = np.array(pdf["features"].tolist())
                pdf["features"] = list(fourier_features(x, dim, width, seed))
            yield pdf

    return data.mapInPandas(run, data.schema)


def _pages(spark: SparkSession, sf_dir: str, buckets: int = 256) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages", ["page_id", "url", "html"])
    median = pages.agg(F.percentile(F.length("html"), F.lit(0.5)).alias("m"))
    labelled = pages.join(F.broadcast(median)).select("page_id", "url", F.when(F.length("html") > F.col("m"), 1.0).otherwise(-1.0).alias("label"))
    long = X.token_buckets(labelled, "page_id", "url", buckets)
    packed = long.groupBy("page_id").agg(F.map_from_entries(F.collect_list(F.struct("feature", "value"))).alias("m")).join(labelled.select("page_id", "label"), "page_id")
    dense = F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda i: F.coalesce(F.try_element_at("m", i.cast("long")), F.lit(0.0)))
    key = F.col("page_id").cast("string")
    return packed.select(F.col("page_id").alias("instance_id"), X.shard_of(key, 16).alias("shard"), X.hash_split(key, 20).alias("is_valid"), dense.alias("features"), "label")


def load_task(spark: SparkSession, sf_dir: str, name: str) -> Workload:
    line = ["x1", "x2", "x3", "x4", "x0"]
    l1 = Penalty("l1", 1e-5)
    if name == "net_price":
        return Workload(name, X.as_instances(X.net_price(spark, sf_dir), line), Linear("logistic", 5), 2.0)
    if name == "net_price_hinge":
        return Workload(name, X.as_instances(X.net_price(spark, sf_dir), line), Linear("hinge", 5, Penalty("l2", 1e-5)), 0.5)
    if name == "net_price_regression":
        base = X.net_price(spark, sf_dir)
        scaled = base.withColumn("label", (F.col("net") - 50000.0) / 29000.0)
        return Workload(name, X.as_instances(scaled, line), Linear("squared", 5), 0.05)
    if name == "kernel":
        return Workload(name, _fourier(X.planted_embeddings(spark, sf_dir, 2)), Linear("hinge", 128, Penalty("l2", 1e-4)), 0.5)
    if name.startswith("kernel_given_"):
        return Workload(name, _fourier(X.given_embeddings(spark, sf_dir, int(name.rpartition("_")[2]))), Linear("hinge", 128, Penalty("l2", 1e-4)), 0.5)
    if name in ("doc_quality", "doc_toxic"):
        return Workload(name, X.document_quality(spark, sf_dir, name[4:]), Linear("logistic", 256, l1), 2.0)
    if name in ("doc_sparse", "toxic_sparse"):
        return Workload(name, X.sparse_documents(spark, sf_dir, "toxic" if name == "toxic_sparse" else "quality"), Linear("logistic", 1 << 18, l1), 8.0)
    if name == "page_sparse":
        return Workload(name, X.sparse_pages(spark, sf_dir), Linear("logistic", 1 << 18, l1), 8.0)
    if name == "page_url":
        return Workload(name, _pages(spark, sf_dir), Linear("logistic", 256, l1), 2.0)
    if name == "planted_ten":
        return Workload(name, X.planted_embeddings(spark, sf_dir, 10), Mlp((64, 32, 10), "tanh"), 0.5)
    if name == "given_ten":
        return Workload(name, X.given_embeddings(spark, sf_dir), Mlp((64, 32, 10), "tanh"), 0.5)
    if name == "augmented":
        return Workload(name, X.planted_embeddings(spark, sf_dir, 10, copies=128, late=True), Mlp((64, 32, 10), "tanh"), 0.5, 512)
    if name == "event_value":
        own = X.event_values(spark, sf_dir)
        columns = [c for c in own.columns if c not in ("instance_id", "label")]
        key = own.withColumn("instance_id", F.col("instance_id").cast("string")).withColumn("one", F.lit(1.0))
        scale = own.agg(F.avg("label").alias("_mean"), F.stddev_pop("label").alias("_std"), F.max("k").alias("_k"))
        wide = key.join(F.broadcast(scale)).withColumn("label", (F.col("label") - F.col("_mean")) / F.col("_std")).withColumn("k", F.coalesce(F.col("k") / F.greatest("_k", F.lit(1.0)), F.lit(0.0)))
        return Workload(name, X.as_instances(wide, [*columns, "one"]), Linear("squared", len(columns) + 1), 0.05)
    if name == "pca":
        own = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
        key = F.col("vec_id").cast("string")
        data = own.select(F.col("vec_id").alias("instance_id"), X.shard_of(key, SHARDS).alias("shard"), F.lit(False).alias("is_valid"), F.col("embedding").cast("array<double>").alias("features"), F.lit(None).cast("double").alias("label"))
        return Workload(name, data, Pca(64, 4), 0.05)
    if name == "identical":
        one = X.as_instances(X.net_price(spark, sf_dir).orderBy("instance_id").limit(1), line, valid_pct=0)
        copies = one.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(1000)))).withColumn("instance_id", F.concat_ws("#", "instance_id", "copy"))
        return Workload(name, copies.withColumn("shard", F.pmod("copy", F.lit(SHARDS)).cast("int")).drop("copy"), Linear("logistic", 5), 0.5)
    if name == "no_signal":
        base = X.net_price(spark, sf_dir, ("l_returnflag",))
        return Workload(name, X.as_instances(base.withColumn("label", F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0)), line), Linear("logistic", 5), 0.1)
    raise ValueError(name)


SHARDS = 16
BLOCK = 1000  # steps whose draws are prefetched together
WORKLOADS = ("net_price", "net_price_hinge", "net_price_regression", "kernel", "kernel_given_0", "doc_quality", "doc_toxic", "doc_sparse", "toxic_sparse", "page_sparse", "page_url", "planted_ten", "given_ten", "augmented", "event_value", "pca", "identical", "no_signal")


def run_methods(spark: SparkSession, w: Workload, steps: int, seeds: tuple[int, ...] = (11,), methods: tuple[str, ...] = ("uniform", "history", "staged"), batch: int | None = None, eta: float | None = None, eval_every: int = 100, beta: float = 0.2, data: DataFrame | None = None, **options) -> DataFrame:
    """Traces of the methods on all rows of one workload, for each seed.

    `uniform` and `history` draw from the whole table in blocks of BLOCK prefetched steps.  `staged`
    spends the steps on SHARDS stages, one shard each; with `visits` a stage makes that many draws
    a row instead.  Other methods go from shard to shard too, without the stages' pull.
    """
    batch, eta = batch or w.batch, eta or w.eta
    data = sharded(w.data) if data is None else data
    prox = w.objective.penalty.kind == "l1"
    visits = options.pop("visits", None)
    traces = None
    for seed in seeds:
        for m in methods:
            common = {"step_rule": constant(eta), "seed": seed, "eval_every": eval_every, "prox": prox, "measure_variance": True, "beta": beta}
            if m in ("uniform", "history"):
                r = T.train(m, data, w.objective, steps=steps, batch=batch, exec_mode=f"prefetch:{BLOCK}", **common, **options)
            else:
                plan = {"visits": visits} if visits else {"inner_steps": -(-steps // SHARDS)}
                if m == "staged":
                    plan |= {"redraw_every": 8, "history": "exact_scan"}
                else:
                    plan |= {"method": m.removeprefix("shard_").removesuffix("_single"), "proximity": "none", "history": "reset"}
                r = T.staged_history(data, w.objective, SHARDS, shards=SHARDS, batch=1 if m == "uniform_single" else batch, **plan, **common, **options)
            one = r.trace_df(spark, m, seed)
            traces = one if traces is None else traces.unionByName(one)
    return traces


def trace_query(name: str, methods: tuple[str, ...], steps: int, **o):
    def q(spark: SparkSession, sf_dir: str) -> DataFrame:
        return run_methods(spark, load_task(spark, sf_dir, name), steps, methods=methods, **o)

    return q


def variance_query(name: str, visits: int = 16, history_visits: int = 2):
    """Variance ratio to uniform draws as training goes on, after each of 16 stages.

    Look j of either method is over the same rows, those of shard j.  The staged run makes `visits`
    draws a row in each stage, the other `history_visits` draws a row in all.
    """

    def q(spark: SparkSession, sf_dir: str) -> DataFrame:
        w = load_task(spark, sf_dir, name)
        data = sharded(w.data)
        n = data.where("not is_valid").count()
        steps = max(SHARDS, history_visits * n // w.batch // SHARDS * SHARDS)
        prox = w.objective.penalty.kind == "l1"
        common = {"step_rule": constant(w.eta), "seed": 11, "prox": prox, "measure_variance": True}
        staged = T.staged_history(data, w.objective, SHARDS, shards=SHARDS, visits=visits, batch=w.batch, eval_every=1 << 30, redraw_every=8, history="exact_scan", **common)
        flat = T.train("history", data, w.objective, steps=steps, batch=w.batch, exec_mode=f"prefetch:{BLOCK}", eval_every=steps // SHARDS, look_shards=SHARDS, **common)
        rows = [(m, j, t["step"], t["loss"], t["error"], t["var_ratio"]) for m, r in (("staged", staged), ("history", flat)) for j, t in enumerate(r.trace)]
        rows += [("uniform", j, t["step"], None, None, 1.0) for j, t in enumerate(flat.trace)]
        return spark.createDataFrame(rows, "method string, look int, step long, loss double, error double, var_ratio double")

    return q


def _reached(trace: list[dict], target: float) -> tuple[int, float, bool]:
    hit = next((t for t in trace if t["error"] is not None and t["error"] <= target), None)
    last = hit or trace[-1]
    return last["step"], last["elapsed_s"], hit is not None


SUBSET = 3000  # rows a stage holds on a large table


def steps_query(name: str = "net_price", seeds: tuple[int, ...] = (31, 32, 33, 34, 35)):
    """Steps and seconds to the error that uniform draws settle at (median of their last quarter).

    one_subset  one subset's rows, small batches: stored lengths against uniform draws
    subsets     fresh subsets of SUBSET rows, 16 visits a row, batch 128: stages against uniform draws
    The steps are large, so the pull is small.  Subsets are drawn from the whole table.  Each run is timed inside its tasks, so both methods of
    a form differ by their own work only.
    """

    def q(spark: SparkSession, sf_dir: str) -> DataFrame:
        w = load_task(spark, sf_dir, name)
        data = sharded(w.data)
        held = D.subset_without_replacement(data.where("is_valid"), SUBSET, 3, 0).drop("u")
        own_rows = checkpointed(D.subset_without_replacement(data.where("not is_valid"), SUBSET, 2, 0).drop("u").unionByName(held), "subset")
        every = checkpointed(data.where("not is_valid").unionByName(held), "instances")
        out = []
        for form, batch, eta, methods in (("one_subset", 32, 10.0, ("uniform", "history")), ("subsets", 128, 30.0, ("uniform", "staged"))):
            runs: dict[str, list] = {m: [] for m in methods}
            for seed in seeds:
                for m in methods:
                    common = {"step_rule": constant(eta), "seed": seed, "eval_every": 25, "batch": batch}
                    if form == "one_subset":
                        own = {"redraw_every": 16, "init": "exact_scan"} if m == "history" else {}
                        r = T.train(m, own_rows, w.objective, steps=2000, **common, **own)
                    else:
                        own = {"redraw_every": 16, "history": "exact_scan", "gamma0": 0.001} if m == "staged" else {"method": "uniform", "proximity": "none", "history": "reset"}
                        r = T.staged_history(every, w.objective, 2, subset_rows=SUBSET, visits=16, **common, **own)
                    runs[m].append(r.trace)
            target = float(np.median([t["error"] for trace in runs["uniform"] for t in trace[-max(1, len(trace) // 4) :]]))
            found = {m: [_reached(t, target) for t in traces] for m, traces in runs.items()}
            base_steps, base_s = (np.mean([f[k] for f in found["uniform"]]) for k in (0, 1))
            for m, hits in found.items():
                steps, secs = [h[0] for h in hits], [h[1] for h in hits]
                out.append((form, m, target, float(np.mean(steps)), float(np.std(steps)), float(np.mean(secs)), sum(h[2] for h in hits), len(hits), float(np.mean([t[-1]["error"] for t in runs[m]])), float(np.mean(steps) / base_steps), float(base_s / np.mean(secs))))
        return spark.createDataFrame(out, "form string, method string, target double, steps double, steps_std double, seconds double, reached int, runs int, last_error double, steps_ratio double, speedup double")

    return q


def time_per_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds a step of uniform draws, stored lengths and stages on four tasks; extra time over uniform.

    All three run on the rows of one shard, as a stage does; the least of three runs counts.
    """
    out = []
    for name in ("net_price", "doc_sparse", "planted_ten", "augmented"):
        w = load_task(spark, sf_dir, name)
        own = checkpointed(w.data.where("shard = 0"), "subset")
        each = {}
        for m in ("uniform", "history", "staged"):
            runs = []
            for seed in (1, 2, 3):
                common = {"step_rule": constant(w.eta), "seed": seed, "eval_every": 150, "batch": w.batch, "prox": w.objective.penalty.kind == "l1"}
                if m == "staged":
                    r = T.staged_history(own, w.objective, 1, shards=1, inner_steps=150, redraw_every=8, **common)
                else:
                    r = T.train(m, own, w.objective, steps=150, **({"redraw_every": 8} if m == "history" else {}), **common)
                runs.append(r.trace[-1]["elapsed_s"] / 150)
            each[m] = min(runs)
        out += [(name, m, w.batch, s, s / each["uniform"] - 1) for m, s in each.items()]
    return spark.createDataFrame(out, "task string, method string, batch int, s_per_step double, overhead double")


def batch_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variance of one step by batch size, for uniform draws and stored lengths, after the same training."""
    w = load_task(spark, sf_dir, "net_price")
    data = sharded(w.data)
    run = T.train("history", data, w.objective, steps=400, batch=128, step_rule=constant(0.5), seed=11, exec_mode=f"prefetch:{BLOCK}", eval_every=400)
    every = data.withColumn("instance_id", F.col("instance_id").cast("string")).join(run.history.select("instance_id", "magnitude"), "instance_id")
    _, total, n = T._mixture_masses(every.where("not is_valid"), 0.2)
    seen = T.look(every, w.objective, run.model, 0.2, total, n)
    out = [(b, m, seen[f"var_{m}"] / b) for b in (1, 4, 16, 128, 512) for m in ("uniform", "history")]
    return spark.createDataFrame(out, "batch int, method string, variance double")


def beta_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = load_task(spark, sf_dir, "net_price")
    data, out = sharded(w.data), None
    for beta in (0.05, 0.2, 0.5, 1.0):
        t = run_methods(spark, w, 400, methods=("history",), beta=beta, eval_every=400, data=data).withColumn("beta", F.lit(beta))
        out = t if out is None else out.unionByName(t)
    return out.select("beta", "loss", "error", "var_ratio", "max_weight")


def staging_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Staged runs with fresh subsets, fixed shards, without the pull, and other ways to carry lengths."""
    w = load_task(spark, sf_dir, "net_price")
    data, out = sharded(w.data), None
    for tag, o in {"fixed": {}, "fresh": {"subset_rows": 1000}, "no_pull": {"proximity": "none"}, "reset": {"history": "reset"}, "scan": {"history": "exact_scan"}}.items():
        t = T.staged_history(data, w.objective, 2, batch=64, inner_steps=100, step_rule=constant(1.0), seed=13, eval_every=100, measure_variance=True, **o).trace_df(spark, tag, 13)
        out = t if out is None else out.unionByName(t)
    return out


def staging_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where the staged method's own numbers lead: subset size, visits a row, pull and shards."""
    w = load_task(spark, sf_dir, "net_price")
    data, out = sharded(w.data), []
    grid = [("subset_rows", m, {"subset_rows": m}) for m in (500, 1000, 3000)]
    grid += [("visits", g, {"visits": g, "subset_rows": 1000}) for g in (4, 16)]
    grid += [("gamma0", g, {"gamma0": g, "subset_rows": 1000}) for g in (0.01, 1.0)]
    grid += [("shards", k, {"shards": k}) for k in (8, 16)]
    for name, value, o in grid:
        own = data if name != "shards" or value == SHARDS else data.withColumn("shard", F.pmod("shard", F.lit(value)).cast("int"))
        plan = o if "visits" in o else {"inner_steps": 120} | o
        r = T.staged_history(own, w.objective, 2, batch=64, step_rule=constant(1.0), seed=13, eval_every=1 << 30, measure_variance=True, redraw_every=8, **plan)
        last = r.trace[-1]
        out.append((name, float(value), last["step"], last["loss"], last["error"], last["var_ratio"], last["elapsed_s"]))
    return spark.createDataFrame(out, "parameter string, value double, step long, loss double, error double, var_ratio double, elapsed_s double")


def scaling_in_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stored lengths against stages as the table grows: the same steps on 1 to 16 shards' rows.

    With more rows a stored length is seen again less often, so its variance ratio falls later;
    the staged method's subsets stay as small as they were.
    """
    w = load_task(spark, sf_dir, "net_price")
    data, out = sharded(w.data), []
    for shards in (1, 4, 16):
        own = data.where(F.col("shard") < shards)
        n = own.where("not is_valid").count()
        steps = 600
        common = {"step_rule": constant(w.eta), "seed": 11, "batch": 128, "measure_variance": True}
        flat = T.train("history", own, w.objective, steps=steps, exec_mode=f"prefetch:{steps // 3}", eval_every=steps, **common)
        staged = T.staged_history(own, w.objective, 2, subset_rows=min(3000, n), inner_steps=steps // 2, eval_every=1 << 30, redraw_every=8, **common)
        out += [(m, n, steps, r.trace[-1]["loss"], r.trace[-1]["error"], r.trace[-1]["var_ratio"], steps * 128 / n) for m, r in (("history", flat), ("staged", staged))]
    return spark.createDataFrame(out, "method string, rows long, steps long, loss double, error double, var_ratio double, visits double")


def all_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = load_task(spark, sf_dir, "net_price")
    return run_methods(spark, w, 160, methods=("uniform", "history", "staged", "full_gradient", "uniform_single", "sequential", "infogain", "infogain_draw", "exact", "snapshot"), batch=16, eta=0.5, eval_every=80)


def prefetch_and_per_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distributed forms: one job a step, and blocks of prefetched steps, from the same draws."""
    w = load_task(spark, sf_dir, "net_price")
    data, rows = sharded(w.data), []
    for mode in ("per_step", "prefetch:1", "prefetch:3"):
        r = T.train("history", data, w.objective, steps=3, batch=16, step_rule=constant(0.5), seed=3, exec_mode=mode, init="exact_scan", eval_every=3)
        t = r.trace[-1]
        rows.append((mode, [round(float(v), 6) for v in r.model], t["loss"], t["error"], t["var_ratio"], t["max_weight"]))
    return spark.createDataFrame(rows, "mode string, model array<double>, loss double, error double, var_ratio double, max_weight double")


def distributed_augmented(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Synchronous steps of 512 over all augmented rows, one job a step: uniform, stored, staged."""
    w = load_task(spark, sf_dir, "augmented")
    data, traces = sharded(w.data), None
    common = {"batch": 512, "step_rule": constant(w.eta), "seed": 11}
    runs = {m: T.train(m, data, w.objective, steps=4, exec_mode="per_step", eval_every=4, init="exact_scan", **common) for m in ("uniform", "history")}
    runs["staged"] = T.staged_history(data, w.objective, 2, shards=SHARDS, inner_steps=2, exec_mode="per_step", eval_every=2, init="exact_scan", **common)
    for m, r in runs.items():
        one = r.trace_df(spark, m, 11)
        traces = one if traces is None else traces.unionByName(one)
    return traces


def communication_per_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes between driver and tasks in synchronous steps of 512 augmented rows."""
    w = load_task(spark, sf_dir, "augmented")
    data, out = sharded(w.data), []
    for m in ("uniform", "history"):
        r = T.train(m, data, w.objective, steps=2, batch=512, step_rule=constant(w.eta), seed=11, exec_mode="per_step", eval_every=0)
        out += [(m, s["step"], s["tasks"], s["down"], s["up"], s["lengths"], s["lengths"] / (s["down"] + s["up"])) for s in r.extra["sent"]]
    return spark.createDataFrame(out, "method string, step long, tasks int, model_bytes long, gradient_bytes long, length_bytes long, extra_share double")


LAYERS = ((10, 64), (32, 64), (128, 128), (256, 512))


def length_cost_timed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Time of row lengths beside the gradient's, for layers of m outputs and l inputs, and the formula's share.

    Both are timed inside the tasks over all embeddings, 128 rows at a time; a row's inputs repeat its
    values up to the layer's width, its outputs are the same from the end.
    """

    def run(batches):
        spent = {layer: np.zeros(3) for layer in LAYERS}
        for pdf in batches:
            e = np.array(pdf["x"].tolist(), dtype=np.float64).reshape(len(pdf), -1)
            for at in range(0, len(e), 128):
                block = e[at : at + 128]
                for (m, l), total in spent.items():
                    wide = np.tile(block, (1, -(-max(m, l) // block.shape[1])))
                    x, d = np.ascontiguousarray(wide[:, :l]), np.ascontiguousarray(wide[:, ::-1][:, :m])
                    work = (lambda d=d, x=x: d.T @ x), (lambda d=d, x=x: np.sqrt((d * d).sum(axis=1) * (x * x).sum(axis=1)))
                    if not total[0]:  # the first calls count no time
                        work[0](), work[1]()
                    total[0] += len(block)
                    for k in (0, 1):
                        began = time.perf_counter()
                        work[k]()
                        total[1 + k] += time.perf_counter() - began
        yield pd.DataFrame([(m, l, int(t[0]), t[1], t[2]) for (m, l), t in spent.items()], columns=["outputs", "inputs", "rows", "gradient", "lengths"])

    own = read_table(spark, sf_dir, "embeddings", ["embedding"]).where("size(embedding) > 0")
    timed = own.select(F.col("embedding").cast("array<double>").alias("x")).mapInPandas(run, "outputs int, inputs int, rows long, gradient double, lengths double")
    whole = timed.groupBy("outputs", "inputs").agg(F.sum("rows").alias("rows"), F.sum("gradient").alias("gradient"), F.sum("lengths").alias("lengths"))
    formula = (F.col("outputs") + F.col("inputs")) / (F.col("outputs") * F.col("inputs"))
    return whole.select("outputs", "inputs", "rows", formula.alias("formula"), F.try_divide("lengths", "gradient").alias("timed"))


def one_vs_rest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each given label against the rest on kernel features: traces of ten two-class tasks."""
    out = None
    for c in range(10):
        t = run_methods(spark, load_task(spark, sf_dir, f"kernel_given_{c}"), 100, methods=("history",)).withColumn("label", F.lit(c))
        out = t if out is None else out.unionByName(t)
    return out


def sparse_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One full proximal step from zero over sparse documents: the largest parameters."""
    w = load_task(spark, sf_dir, "doc_sparse")
    rows = w.data.withColumn("weight", F.lit(1.0))
    g, n, *_ = T.distributed_gradient(rows, w.objective, w.objective.start())
    model = Penalty("l1", 1e-3).shrink(-8.0 * g / n, 8.0)
    kept = np.flatnonzero(model)
    found = spark.createDataFrame([(int(i), float(model[i])) for i in kept], "feature long, value double")  # the model's non-zeros
    return found.select("feature", F.round("value", 6).alias("value"))


SPARSE_STEP_SQL = """WITH t AS (SELECT d.doc_id, unnest(list_filter(regexp_split_to_array(lower(d.text), '[^\\p{L}\\p{N}]+'), lambda x: x <> '')) AS word FROM documents d JOIN labels l USING (doc_id) WHERE l.quality IS NOT NULL),
c AS (SELECT doc_id, ('0x' || substr(md5(word), 1, 8))::BIGINT % 262144 AS feature, count(*)::DOUBLE AS n FROM t GROUP BY 1, 2),
s AS (SELECT doc_id, feature, n / sqrt(sum(n * n) OVER (PARTITION BY doc_id)) AS value FROM c),
g AS (SELECT feature, sum(-0.5 * (2.0 * quality - 1.0) * value) / (SELECT count(DISTINCT doc_id) FROM t) AS g FROM s JOIN labels USING (doc_id) GROUP BY feature),
m AS (SELECT feature, sign(-8.0 * g) * greatest(abs(8.0 * g) - 8.0 * 0.001, 0.0) AS value FROM g)
SELECT feature, round(value, 6) AS value FROM m WHERE value <> 0"""


def queries() -> dict[str, tuple]:
    hist = ("uniform", "history", "staged")
    own = {
        "train_uniform_trace": trace_query("net_price", ("uniform",), 600, eval_every=200),
        "train_history_trace": trace_query("net_price", ("history",), 600, eval_every=200),
        "train_staged_trace": trace_query("net_price", ("staged",), 600, visits=16, eval_every=1 << 30),
        "train_hinge_trace": trace_query("net_price_hinge", hist, 304),
        "train_regression_trace": trace_query("net_price_regression", hist, 304),
        "train_event_trace": trace_query("event_value", hist, 304),
        "train_kernel_trace": trace_query("kernel", hist, 304),
        "train_kernel_one_vs_rest": one_vs_rest,
        "train_doc_quality_trace": trace_query("doc_quality", hist, 304),
        "train_doc_toxic_trace": trace_query("doc_toxic", hist, 304),
        "train_doc_sparse_trace": trace_query("doc_sparse", hist, 304),
        "train_page_sparse_trace": trace_query("page_sparse", hist, 304),
        "train_page_url_trace": trace_query("page_url", hist, 304),
        "train_mlp_trace": trace_query("planted_ten", hist, 304),
        "train_given_ten_trace": trace_query("given_ten", hist, 304),
        "train_augmented_trace": trace_query("augmented", hist, 96),
        "train_pca_trace": trace_query("pca", hist, 208),
        "train_identical_trace": trace_query("identical", hist, 64, eval_every=64),
        "train_no_signal_trace": trace_query("no_signal", hist, 208),
        "train_all_methods": all_methods,
        "variance_over_training": variance_query("net_price"),
        "variance_over_training_sparse": variance_query("doc_sparse"),
        "variance_over_training_network": variance_query("planted_ten"),
        "variance_over_training_augmented": variance_query("augmented", history_visits=1),
        "steps_to_target": steps_query(),
        "time_per_step": time_per_step,
        "length_cost_timed": length_cost_timed,
        "batch_size_sweep": batch_sweep,
        "beta_sweep": beta_sweep,
        "staging_ablation": staging_ablation,
        "staging_grid": staging_grid,
        "scaling_in_rows": scaling_in_rows,
        "distributed_modes": prefetch_and_per_step,
        "distributed_augmented": distributed_augmented,
        "communication_per_step": communication_per_step,
    }
    return {k: (v, None) for k, v in own.items()} | {"sparse_proximal_step": (sparse_step, SPARSE_STEP_SQL)}
