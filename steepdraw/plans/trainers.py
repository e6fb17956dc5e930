"""Training methods over instances (instance_id, shard, is_valid, features, label).

Three ways to run the same steps:

* stage_local - a stage is one task that reads its shards and runs all of the stage's steps;
* per_step - each step is a distributed job: draws by shard masses, a broadcast join to fetch
  the rows, one partial gradient a task, an update on the driver;
* prefetch - k steps are drawn in one job under frozen probabilities, then run in one task.

Shards are random, so any of them is a uniform subset and a stage is a pruned read.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.features import shifted
from ..functions.objectives import SparseRows
from ..functions.steps import StepRule, constant
from ..operators import draws as D
from ..operators import history as H
from ..sources.tables import checkpointed, collected, dropped, only_reads
from . import local

TRACE = "method string, seed long, step long, stage int, loss double, penalty double, error double, nonzero int, var_ratio double, max_weight double, elapsed_s double"
INPUTS = ("places", "source", "copy", "features", "label")  # what a row's features and label are made from
STATE = "kind string, stage int, instance_id string, magnitude double, last_step long, visits long, vector array<double>, trace string"


@dataclass
class TrainResult:
    model: np.ndarray
    trace: list[dict]
    history: DataFrame | None = None
    status: str = "done"
    extra: dict = field(default_factory=dict)

    def trace_df(self, spark, method: str, seed: int) -> DataFrame:
        rows = [(method, seed, t["step"], t["stage"], t["loss"], t["penalty"], t["error"], t["nonzero"], t["var_ratio"], t["max_weight"], t["elapsed_s"]) for t in self.trace]
        return spark.createDataFrame(rows, TRACE)


def _matrix(pdf: pd.DataFrame) -> tuple[np.ndarray | SparseRows, np.ndarray | None]:
    """Rows and labels of a batch; with a column `places`, features hold the values at those places, with `copy` those of the row's source."""
    if "places" in pdf:
        x = SparseRows.of(pdf["places"].tolist(), pdf["features"].tolist())
    else:
        x = np.array(pdf["features"].tolist(), dtype=np.float64).reshape(len(pdf), -1)
        if "copy" in pdf:
            x = shifted(x, [None if pd.isna(v) else int(v) for v in pdf["source"]], pdf["copy"].to_numpy())
    return x, None if pdf["label"].isna().all() else pdf["label"].to_numpy(dtype=np.float64)


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Sizes and values of lists, without an object for each."""
    if column.null_count:
        raise ValueError("rows without features cannot be trained on")
    return pc.list_value_length(column).to_numpy(zero_copy_only=False), column.flatten().to_numpy(zero_copy_only=False)


def _arrow_matrix(batch: pa.RecordBatch) -> tuple[np.ndarray | SparseRows, np.ndarray | None]:
    """_matrix of an Arrow batch."""
    sizes, values = _lists(batch.column("features"))
    values = values.astype(np.float64)
    if "places" in batch.schema.names:
        x = SparseRows(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64), _lists(batch.column("places"))[1].astype(np.int64), values)
    else:
        if len(sizes) and (sizes != sizes[0]).any():
            raise ValueError("rows of features differ in size")
        x = values.reshape(len(sizes), -1) if len(sizes) else values.reshape(0, 0)
        if "copy" in batch.schema.names:
            x = shifted(x, batch.column("source").to_pylist(), batch.column("copy").to_numpy(zero_copy_only=False))
    label = batch.column("label")
    return x, None if label.null_count == len(label) else label.cast(pa.float64()).to_numpy(zero_copy_only=False)


def _joined(parts: list) -> tuple[np.ndarray | SparseRows | None, np.ndarray | None]:
    """Rows and labels of batches as one matrix; the list is emptied."""
    xs, ys = [x for x, _ in parts if len(x)], [y for x, y in parts if len(x)]
    parts.clear()
    if not xs:
        return None, None
    y = None if all(y is None for y in ys) else np.concatenate([np.full(len(x), np.nan) if y is None else y for x, y in zip(xs, ys, strict=True)])
    if isinstance(xs[0], SparseRows):
        sizes = np.concatenate([np.diff(x.edges) for x in xs])
        return SparseRows(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64), np.concatenate([x.places for x in xs]), np.concatenate([x.values for x in xs])), y
    if len({x.shape[1] for x in xs}) > 1:
        raise ValueError("rows of features differ in size")
    whole, at = np.empty((sum(map(len, xs)), xs[0].shape[1])), 0
    while xs:  # each part goes as soon as it is copied
        x = xs.pop(0)
        whole[at : at + len(x)] = x
        at += len(x)
    return whole, y


OUT_ROWS = 50_000


def _stage_task(obj, w: np.ndarray, options: dict):
    """One stage in one task: rows in, model, trace and history rows out.

    Rows come in order and are held as arrays only, so a stage takes little more than its numbers.
    """
    import json

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stage = options.get("stage", 0)
        own, held, ids, more = [], [], [], {"magnitude": [], "prob": []}
        for batch in batches:
            valid = batch.column("is_valid")
            mine = batch.filter(pc.invert(valid))
            own.append(_arrow_matrix(mine))
            held.append(_arrow_matrix(batch.filter(valid)))
            ids.append(mine.column("instance_id").cast(pa.string()))
            for c in more:
                if c in batch.schema.names:
                    more[c].append(mine.column(c).cast(pa.float64()).to_numpy(zero_copy_only=False))
        x, y = _joined(own)
        if x is None:
            yield _state([("model", stage, None, None, None, None, w.tolist(), "[]")])
            return
        xv, yv = _joined(held)
        own = held = None
        opts = dict(options)
        keep = opts.pop("keep_rows", True)
        if more["magnitude"] and opts.pop("use_history", False):
            opts["magnitude"] = np.concatenate(more["magnitude"])
        opts.pop("use_history", None)
        began = time.perf_counter()
        if opts.pop("init", "") == "exact_scan":
            opts["magnitude"] = local.whole_pass(obj, w, x, y)[1]
        scan = time.perf_counter() - began
        if opts["method"] in ("weighted", "biased"):
            opts["prob"] = np.concatenate(more["prob"])
        s = local.run_steps(obj, x, y, w, x_valid=xv, y_valid=yv, **opts)
        s.trace = [t | {"elapsed_s": t["elapsed_s"] + scan} for t in s.trace]
        yield _state([("model", stage, s.status, float(s.max_weight), 0, 0, s.w.tolist(), json.dumps(s.trace))])
        at = np.flatnonzero(s.visits > 0) if keep else np.zeros(0, dtype=np.int64)
        names = pa.chunked_array(ids, pa.string())
        for k in range(0, len(at), OUT_ROWS):
            some = at[k : k + OUT_ROWS]
            n = len(some)
            columns = [pa.array(["row"] * n), pa.array(np.full(n, stage, np.int32)), names.take(pa.array(some)).combine_chunks(), pa.array(s.magnitude[some]), pa.array(s.last_step[some]), pa.array(s.visits[some]), pa.nulls(n, pa.list_(pa.float64())), pa.nulls(n, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, schema=_STATE)

    return run


_STATE = pa.schema([("kind", pa.string()), ("stage", pa.int32()), ("instance_id", pa.string()), ("magnitude", pa.float64()), ("last_step", pa.int64()), ("visits", pa.int64()), ("vector", pa.list_(pa.float64())), ("trace", pa.string())])


def _state(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), _STATE.types, strict=True)], schema=_STATE)


def _features_made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if batch.num_rows:
            x = _arrow_matrix(batch)[0]
            made = pa.ListArray.from_arrays(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1], x.ravel())
            kept = batch.drop_columns(["source", "copy"])
            yield kept.set_column(kept.schema.get_field_index("features"), "features", made)


def _made(data: DataFrame) -> DataFrame:
    """Rows with the features of their copies, made in the tasks that read them, not in the one that trains."""
    if "copy" not in data.columns:
        return data
    kinds = {c: k for c, k in data.dtypes if c not in ("source", "copy")} | {"features": "array<double>"}
    return data.mapInArrow(_features_made, ", ".join(f"{c} {k}" for c, k in kinds.items()))


def stage_run(data: DataFrame, obj, w: np.ndarray, **options) -> tuple[np.ndarray, list[dict], DataFrame | None, str]:
    """All steps of a stage on the rows of `data`, which must fit one task; keep_rows=False leaves out their lengths."""
    import json

    kept = [c for c in ("instance_id", "is_valid", *INPUTS, "magnitude", "prob") if c in data.columns]
    own = _made(data.select(*kept)).repartition(1).sortWithinPartitions(F.col("instance_id").asc_nulls_last())
    out = own.mapInArrow(_stage_task(obj, w, options), STATE)
    if not options.get("keep_rows", True):  # only the model's row comes out, and it is read once
        head = out.select("vector", "trace", "instance_id").first()
        return np.array(head["vector"]), json.loads(head["trace"]), None, head["instance_id"] or "done"
    out = checkpointed(out, "stage")
    head = out.where("kind = 'model'").select("vector", "trace", "instance_id").first()
    rows = out.where("kind = 'row'").select("instance_id", "magnitude", "last_step", "visits")
    return np.array(head["vector"]), json.loads(head["trace"]), rows, head["instance_id"] or "done"


def _wrong_rows(obj, w: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = wrong = 0
        for batch in batches:
            if batch.num_rows:
                rows, wrong = rows + batch.num_rows, wrong + int(obj.wrong(w, *_arrow_matrix(batch)).sum())
        yield pa.RecordBatch.from_arrays([pa.array([rows]), pa.array([wrong])], names=["rows", "wrong"])

    return run


def held_error(valid: DataFrame, obj, w: np.ndarray) -> float | None:
    """Share of wrong held-out rows, counted in their tasks; None without any."""
    found = valid.select(*_inputs(valid)).mapInArrow(_wrong_rows(obj, w), "rows long, wrong long").agg(F.sum("rows").alias("rows"), F.sum("wrong").alias("wrong")).first()
    return found["wrong"] / found["rows"] if found["rows"] else None


def train(method: str, data: DataFrame, obj, *, steps: int, batch: int = 128, step_rule: StepRule | None = None, seed: int = 0, exec_mode: str = "stage_local", eval_every: int = 100, w: np.ndarray | None = None, **options) -> TrainResult:
    """One method over all rows of data."""
    rule = step_rule or constant(0.1)
    w = obj.start(seed) if w is None else w
    if exec_mode == "stage_local":
        w, trace, rows, status = stage_run(data, obj, w, method=method, steps=steps, batch=batch, rule=rule, seed=seed, eval_every=eval_every, **options)
        return TrainResult(w, trace, rows, status)
    if exec_mode == "per_step":
        return _per_step(method, data, obj, w, steps, batch, rule, seed, eval_every, **options)
    if exec_mode.startswith("prefetch"):
        return _prefetch(method, data, obj, w, steps, batch, rule, seed, eval_every, int(exec_mode.partition(":")[2] or 10), **options)
    raise ValueError(exec_mode)


def uniform_minibatch(data, obj, steps, batch=128, replacement=True, step_rule=None, seed=0, exec_mode="stage_local", **o):
    return train("uniform", data, obj, steps=steps, batch=batch, step_rule=step_rule, seed=seed, exec_mode=exec_mode, **({} if replacement else {"replacement": False}), **o)


def uniform_single(data, obj, steps, **o):
    return uniform_minibatch(data, obj, steps, batch=1, **o)


def full_gradient(data, obj, steps, step_rule=None, **o):
    return train("full_gradient", data, obj, steps=steps, step_rule=step_rule, **o)


def sequential_pass(data, obj, epochs, batch=128, step_rule=None, seed=0, **o):
    """Rows in stored order (shards are random, so stored order is shuffled once)."""
    n = data.where("not is_valid").count()
    return train("sequential", data, obj, steps=epochs * -(-n // batch), batch=batch, step_rule=step_rule, seed=seed, **o)


def infogain_greedy(data, obj, steps, batch=1, gain="entropy", **o):
    return train("infogain", data, obj, steps=steps, batch=batch, gain=gain, **o)


def proportional_infogain(data, obj, steps, batch=1, gain="entropy", floor=0.0, **o):
    return train("infogain_draw", data, obj, steps=steps, batch=batch, gain=gain, floor=floor, **o)


def weighted(data, obj, steps, batch=128, prob_col="prob", reweight=True, **o):
    return train("weighted" if reweight else "biased", data.withColumn("prob", F.col(prob_col)), obj, steps=steps, batch=batch, **o)


def exact_weighted(data, obj, steps, batch=1, floor=0.0, **o):
    return train("exact", data, obj, steps=steps, batch=batch, floor=floor, **o)


def history_weighted(data, obj, steps, batch=128, beta=0.2, init="exact_scan", refresh="pre", exec_mode="stage_local", **o):
    extra = {"init": init, "refresh": refresh} if exec_mode == "stage_local" else {"init": init}
    return train("history", data, obj, steps=steps, batch=batch, beta=beta, exec_mode=exec_mode, **extra, **o)


def snapshot_variance_reduced(data, obj, steps, snapshot_every=100, **o):
    return train("snapshot", data, obj, steps=steps, snapshot_every=snapshot_every, **o)


def proximity_weight(kind: str, gamma0: float, stage: int, rows: int, var: float) -> float:
    """The pull of a stage towards its start; the growing form is this library's choice."""
    return {"none": 0.0, "constant": gamma0, "growing": gamma0 * float(np.sqrt((stage + 1) * max(var, 0.0) / rows))}[kind]


def staged_history(data: DataFrame, obj, stages: int, *, shards: int = 16, subset_rows: int | None = None, visits: int = 16, batch: int = 128, inner_steps: int | None = None, proximity: str = "growing", gamma0: float = 0.1, beta: float = 0.2, history: str = "carry", step_rule: StepRule | None = None, seed: int = 0, eval_every: int = 100, method: str = "history", exec_mode: str = "stage_local", w: np.ndarray | None = None, after_stage=None, **options) -> TrainResult:
    """Stages on random subsets: fixed shards in turn, or `subset_rows` fresh rows each.

    Lengths are carried between stages as a table of deltas, reset, or taken by a scan of the
    subset.  Only the model and the trace of a stage reach the driver.  A stage makes `visits` draws
    a row unless `inner_steps` says otherwise; after the last shard the first comes again.
    after_stage(stage, step, model, lengths) is called at the end of each.
    """
    rule = step_rule or constant(0.1)
    w = obj.start(seed) if w is None else w
    trace: list[dict] = []
    known: DataFrame | None = None
    step, spent, var = 0, 0.0, 1.0
    status, visited_rows, sent = "done", [], []
    valid = data.where("is_valid")
    sizes = {r["shard"]: r["count"] for r in data.where("not is_valid").groupBy("shard").count().collect()} if subset_rows is None else {}  # one row a shard
    for t in range(stages):
        apart = subset_rows is not None and inner_steps is not None and eval_every >= inner_steps and exec_mode == "stage_local" and "stop_error" not in options
        if subset_rows is None:
            own = data.where(F.col("shard") == t % shards)  # a pruned read on a sharded table
        else:
            own = D.subset_without_replacement(data.where("not is_valid"), subset_rows, seed, t).drop("u")
            if apart:  # one look, at the stage's end: all held-out rows are judged in their own tasks
                own = checkpointed(own, "subset")
            else:
                own = own.unionByName(valid)
        extra: dict = {}
        if history == "carry" and known is not None:
            own = H.attach(own.withColumn("instance_id", F.col("instance_id").cast("string")), known)
            if exec_mode == "stage_local":
                extra["use_history"] = True
        elif history == "exact_scan":
            extra["init"] = "exact_scan"
        rows = sizes.get(t % shards, 0) if subset_rows is None else own.where("not is_valid").count()
        visited_rows.append(rows)
        if not rows:
            continue
        inner = inner_steps or max(1, visits * rows // batch)
        gamma = proximity_weight(proximity, gamma0, t, rows, var)
        start = w
        if exec_mode == "stage_local":
            w, found, delta, status = stage_run(own, obj, w, method=method, steps=inner, batch=batch, rule=rule, seed=seed, beta=beta, anchor=start, gamma=gamma, first_step=step, eval_every=eval_every, stage=t, keep_rows=history == "carry", **extra, **options)
            if apart and found:
                error = held_error(valid, obj, w)
                found[-1]["error"] = found[-1]["error"] if error is None else error
        else:  # the subset's rows stay in their tasks
            if "init" not in options:
                extra.setdefault("init", "constant")
            part = train(method, own, obj, steps=inner, batch=batch, step_rule=rule, seed=seed, exec_mode=exec_mode, eval_every=eval_every, w=w, beta=beta, anchor=start, gamma=gamma, first_step=step, stage=t, **extra, **options)
            w, found, status = part.model, part.trace, part.status
            delta = part.history.withColumn("last_step", F.lit(step + inner).cast("long"))
            sent += part.extra.get("sent", [])
        for f in found:
            trace.append(f | {"elapsed_s": f["elapsed_s"] + spent})
        step, spent = step + inner, trace[-1]["elapsed_s"] if trace else 0.0
        if history == "carry":
            fresh = delta.select("instance_id", F.lit(0).alias("shard"), "magnitude", "last_step")
            known = checkpointed(fresh if known is None else H.compact(known, fresh), "history")
        if after_stage is not None:
            after_stage(t, step, w, known)
        collected(data.sparkSession)  # a stage's shuffle files go before the next stage's come
        if status in ("reached", "diverged"):
            break
    return TrainResult(w, trace, known, status, {"subset_rows": visited_rows, "sent": sent})


def _inputs(data: DataFrame) -> list[str]:
    return [c for c in INPUTS if c in data.columns]


def _gradient_rows(obj, w: np.ndarray):
    """Partial gradient, loss and lengths of the rows of a task; one partial a task."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, n, most, ids, lens = None, 0, 0.0, [], []
        for pdf in batches:
            if not len(pdf):
                continue
            x, y = _matrix(pdf)
            _, lengths, gradient = obj.evaluate(w, x, y)
            part = gradient(pdf["weight"].to_numpy(dtype=np.float64))
            most = max(most, float(pdf["weight"].max()))
            total, n = part if total is None else total + part, n + len(pdf)
            ids += pdf["instance_id"].astype(str).tolist()
            lens += lengths.tolist()
        if total is not None:
            yield pd.DataFrame([{"gradient": total.tolist(), "n": n, "most": most, "ids": ids, "lens": lens}])

    return run


def distributed_gradient(rows: DataFrame, obj, w: np.ndarray) -> tuple[np.ndarray, int, dict[str, float], int, float]:
    """Weighted gradient sum of drawn rows, their number, the lengths observed (a batch of rows), the number of partial sums, the largest weight."""
    parts = rows.select("instance_id", *_inputs(rows), "weight").mapInPandas(_gradient_rows(obj, w), "gradient array<double>, n long, most double, ids array<string>, lens array<double>").collect()
    total, seen = np.zeros(len(w)), {}
    for p in sorted(parts, key=lambda r: r["ids"]):
        total += np.array(p["gradient"])
        seen |= dict(zip(p["ids"], p["lens"], strict=True))
    return total, sum(p["n"] for p in parts), seen, len(parts), max((p["most"] for p in parts), default=0.0)


def _lengths(obj, w: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lengths = obj.evaluate(w, *_arrow_matrix(batch))[1] if batch.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column("instance_id"), batch.column("shard"), pa.array(lengths)], names=["instance_id", "shard", "magnitude"])

    return run


def row_lengths(data: DataFrame, obj, w: np.ndarray) -> DataFrame:
    """instance_id, shard, magnitude for any objective, in one narrow pass."""
    kind = dict(data.dtypes)["instance_id"]
    return data.select("instance_id", "shard", *_inputs(data)).mapInArrow(_lengths(obj, w), f"instance_id {kind}, shard int, magnitude double")


def _look_rows(obj, w: np.ndarray, beta: float, total: float, n: int):
    """Partial sums of a task for one look: losses, lengths, inverse probabilities, gradient, held-out errors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, g = np.zeros(6), np.zeros(len(w))
        for batch in batches:
            for held in (False, True):
                own = batch.filter(batch.column("is_valid") if held else pc.invert(batch.column("is_valid")))
                if not len(own):
                    continue
                x, y = _arrow_matrix(own)
                if held:
                    sums[4:] += len(own), obj.wrong(w, x, y).sum()
                    continue
                losses, lengths, gradient = obj.evaluate(w, x, y)
                share = own.column("magnitude").to_numpy(zero_copy_only=False) / total if total > 0 else np.full(len(own), 1 / n)
                p = (1 - beta) * share + beta / n
                sums[:4] += len(own), losses.sum(), (lengths**2).sum(), (lengths**2 / p).sum()
                g += gradient(np.ones(len(own)))
        yield pa.RecordBatch.from_arrays([pa.array([sums]), pa.array([g])], names=["sums", "gradient"])

    return run


def look(base: DataFrame, obj, w: np.ndarray, beta: float, total: float, n: int) -> dict:
    """Mean loss, held-out error and variance ratio at w, in one pass; base holds magnitudes."""
    kept = [c for c in ("is_valid", "magnitude", *INPUTS) if c in base.columns]
    parts = base.select(*kept).mapInArrow(_look_rows(obj, w, beta, total, n), "sums array<double>, gradient array<double>").collect()  # one row a task
    sums = np.sum([p["sums"] for p in parts], axis=0)
    if not sums[0]:  # no row to train on here
        return {"loss": None, "penalty": obj.penalty.value(w), "error": float(sums[5] / sums[4]) if sums[4] else None, "nonzero": int(np.count_nonzero(np.abs(w) > 1e-8)), "var_ratio": None}
    g = np.sum([p["gradient"] for p in parts], axis=0) / sums[0]
    flat, given = sums[2] / sums[0] - g @ g, sums[3] / sums[0] ** 2 - g @ g
    return {"loss": float(sums[1] / sums[0]), "penalty": obj.penalty.value(w), "error": float(sums[5] / sums[4]) if sums[4] else None, "nonzero": int(np.count_nonzero(np.abs(w) > 1e-8)), "var_uniform": float(flat), "var_history": float(given), "var_ratio": float(given / flat) if flat > 1e-15 else 1.0}


class _Stored:
    """Stored lengths of a distributed run: a written table, and what the steps since have seen.

    The lengths seen since are a few rows a step; they are joined by broadcast and, from
    `compact_rows` on, written into the table.  The total is kept up to date on the driver.
    """

    def __init__(self, data: DataFrame, obj, w: np.ndarray, init: str, compact_rows: int = 200_000) -> None:
        own = data.withColumn("instance_id", F.col("instance_id").cast("string"))
        if "magnitude" not in own.columns:
            own = own.withColumn("magnitude", F.lit(1.0))
            if init == "exact_scan":
                kinds = dict(own.dtypes)
                own = own.mapInArrow(_with_lengths(obj, w), ", ".join(f"{c} {kinds[c]}" for c in own.columns))
        self.written = not only_reads(own)  # a table with the same length everywhere is not written again
        self.table, self.seen, self.compact_rows = checkpointed(own, "stored") if self.written else own, {}, compact_rows
        self._now: DataFrame | None = None

    def see(self, ids, lengths) -> None:
        self.seen.update(zip(ids, lengths, strict=True))
        self._now = None

    def current(self) -> DataFrame:
        """All rows with the lengths last seen."""
        if self._now is None:
            self._now = self._joined() if self.seen else self.table
        return self._now

    def _joined(self) -> DataFrame:
        fresh = self.table.sparkSession.createDataFrame(pa.table({"instance_id": pa.array(self.seen, pa.string()), "_seen": pa.array(self.seen.values(), pa.float64())}))
        out = self.table.join(F.broadcast(fresh), "instance_id", "left").withColumn("magnitude", F.coalesce("_seen", "magnitude")).select(*self.table.columns)
        if len(self.seen) >= self.compact_rows:
            last, self.table, self.seen = self.table, checkpointed(out, "stored"), {}
            if self.written:
                dropped(last)
            self.written = True
            return self.table
        return out


def _with_lengths(obj, w: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield batch.set_column(batch.schema.get_field_index("magnitude"), "magnitude", pa.array(obj.evaluate(w, *_arrow_matrix(batch))[1]))

    return run


def _mixture_masses(rows: DataFrame, beta: float) -> tuple[list[tuple], float, int]:
    """(shard, rows, mass) of the drawing probabilities, the sum of lengths and the number of rows."""
    return _mixed(_length_masses(rows), beta)


def _length_masses(rows: DataFrame) -> list[tuple]:
    """(shard, rows, sum of lengths), in order of the shards."""
    return sorted(tuple(r) for r in D.shard_masses(rows, "magnitude").collect())


def _mixed(masses: list[tuple], beta: float) -> tuple[list[tuple], float, int]:
    n, total = sum(r[1] for r in masses), sum(r[2] for r in masses)
    return [(s, c, ((1 - beta) * m / total if total else (1 - beta) * c / n) + beta * c / n) for s, c, m in masses], total, n


def _mixture(beta: float, total: float, n: int):
    share = F.col("magnitude") / F.lit(total) if total else F.lit(1.0 / n)
    return (1 - beta) * share + F.lit(beta / n)


def _per_step(method, data, obj, w, steps, batch, rule, seed, eval_every, beta: float = 0.2, floor: float = 0.0, init: str = "constant", measure_variance: bool = True, anchor=None, gamma: float = 0.0, first_step: int = 0, stage: int = 0, **_) -> TrainResult:
    """One distributed job a step; for tests, large batches and rows that fit no single task.

    A step sends the model to the tasks and one gradient, and the drawn rows' lengths, back:
    `extra` counts those bytes.
    """
    beta = 1.0 if method in ("uniform", "full_gradient") else floor if method == "exact" else beta
    stored = _Stored(data, obj, w, init if method == "history" else "constant")
    trace, sent, max_weight, began, looked = [], [], 0.0, time.perf_counter(), 0.0
    for t in range(first_step + 1, first_step + steps + 1):
        every = stored.current()
        rows = every.where("not is_valid")
        if method == "exact":
            rows = checkpointed(rows.drop("magnitude").mapInPandas(_fresh_lengths(obj, w), ", ".join(f"{c} {k}" for c, k in rows.dtypes)), "lengths")
        if method == "full_gradient":
            drawn = rows.withColumn("weight", F.lit(1.0))
        elif method in ("uniform", "exact", "history"):
            masses, total, n = _mixture_masses(rows, beta)
            picked = D.block_draw(rows.select("instance_id", "shard", _mixture(beta, total, n).alias("prob")), "prob", batch, seed, [t], masses)
            drawn = rows.join(F.broadcast(picked.select("instance_id", "weight")), "instance_id")
        else:
            raise ValueError(f"{method} has no per-step form")
        g, count, seen, parts, most = distributed_gradient(drawn, obj, w)
        max_weight = max(max_weight, most)
        sent.append({"step": t, "tasks": parts, "down": 8 * len(w) * parts, "up": 8 * len(w) * parts, "lengths": sum(len(i) + 8 for i in seen) if method == "history" else 0})
        step = g / count + obj.penalty.gradient(w) + (gamma * (w - anchor) if anchor is not None else 0.0)
        if method == "history":
            stored.see(seen, seen.values())
        if eval_every and ((t - first_step) % eval_every == 0 or t == first_step + steps):
            pass_began = time.perf_counter()
            elapsed = pass_began - began - looked
            w = w - rule.move(step, t)
            after = stored.current()
            masses, total, n = _mixture_masses(after.where("not is_valid"), beta)
            trace.append(look(after, obj, w, beta, total, n) | {"step": t, "stage": stage, "max_weight": max_weight, "elapsed_s": elapsed})
            looked += time.perf_counter() - pass_began
        else:
            w = w - rule.move(step, t)
    state = stored.current().select("instance_id", "shard", "magnitude")
    return TrainResult(w, trace, state, "done", {"sent": sent})


def _fresh_lengths(obj, w: np.ndarray):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield pdf.assign(magnitude=obj.evaluate(w, *_matrix(pdf))[1] if len(pdf) else [])

    return run


BLOCK_ROWS = 200_000


def _prefetch(method, data, obj, w, steps, batch, rule, seed, eval_every, k: int, beta: float = 0.2, init: str = "exact_scan", measure_variance: bool = True, anchor=None, gamma: float = 0.0, first_step: int = 0, stage: int = 0, prox: bool = False, look_shards: int = 0, **_) -> TrainResult:
    """Blocks of k steps: one draw job under frozen probabilities, then k steps over the drawn rows.

    Unbiased for any k, since each draw keeps the probability it was made with.  k * batch rows,
    BLOCK_ROWS at most, reach the driver at a time, whatever the size of the table.  With
    look_shards, look j of the trace is over the rows of shard j modulo look_shards.
    """
    if method not in ("uniform", "history"):
        raise ValueError(f"{method} has no prefetched form")
    beta = 1.0 if method == "uniform" else beta
    k = max(1, min(k, BLOCK_ROWS // batch))
    stored = _Stored(data, obj, w, init if method == "history" else "constant")
    trace, max_weight, began, looked = [], 0.0, time.perf_counter(), 0.0
    sums = None  # of the lengths, until a step changes them
    last, done = first_step + steps, first_step
    while done < last:
        upto = min(done + k, last, (done - first_step) // eval_every * eval_every + eval_every + first_step if eval_every else last)
        now = range(done + 1, upto + 1)
        rows = stored.current().where("not is_valid")
        sums = sums or _length_masses(rows)
        masses, total, n = _mixed(sums, beta)
        picked = D.block_draw(rows.select("instance_id", "shard", _mixture(beta, total, n).alias("prob")), "prob", batch, seed, now, masses)
        inputs = _inputs(rows)
        fetched = stored.table.where("not is_valid").select("instance_id", *inputs).join(F.broadcast(picked), "instance_id").select("step", "draw_no", "instance_id", *inputs, "weight").toArrow().sort_by([("step", "ascending"), ("draw_no", "ascending")]).combine_chunks()
        x, y = _joined([_arrow_matrix(b) for b in fetched.to_batches()])
        ids, weights, at = fetched["instance_id"].to_numpy(), fetched["weight"].to_numpy(), fetched["step"].to_numpy()
        edges = np.searchsorted(at, [*now, upto + 1])
        max_weight = max(max_weight, float(weights.max()))
        for t, a, z in zip(now, edges, edges[1:], strict=False):
            own = np.arange(a, z)
            _, lengths, gradient = obj.evaluate(w, x[own], None if y is None else y[own])
            g = gradient(weights[a:z] / (z - a)) + (0.0 if prox else obj.penalty.gradient(w)) + (gamma * (w - anchor) if anchor is not None else 0.0)
            w = w - rule.move(g, t)
            if prox and obj.penalty.kind == "l1":
                w = obj.penalty.shrink(w, rule.rate(t))
            if method == "history":
                stored.see(ids[a:z], lengths.tolist())
        done = upto
        if method == "history":
            sums = None
        if eval_every and ((done - first_step) % eval_every == 0 or done == last):
            pass_began = time.perf_counter()
            elapsed = pass_began - began - looked
            after = stored.current()
            sums = sums or _length_masses(after.where("not is_valid"))  # the next block's too
            seen_in = sums
            if look_shards:
                own = len(trace) % look_shards
                after, seen_in = after.where(F.col("shard") == own), [r for r in sums if r[0] == own]
            held, count = sum(r[2] for r in seen_in), sum(r[1] for r in seen_in)
            trace.append(look(after, obj, w, beta, held, count) | {"step": done, "stage": stage, "max_weight": max_weight, "elapsed_s": elapsed})
            looked += time.perf_counter() - pass_began
            if trace[-1]["loss"] is not None and not np.isfinite(trace[-1]["loss"]):
                break
    return TrainResult(w, trace, stored.current().select("instance_id", "shard", "magnitude"))
