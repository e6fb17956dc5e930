"""The stochastic loop over rows held by one task: every method, step by step, in NumPy.

Draws come from hash uniforms, so the same rows are drawn whether steps run here or as one Spark
job each.  The stored length of a row is its unweighted gradient length at the parameters before
the step (or after it, with refresh='post'), and is written once for each distinct row of a batch.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np

from ..functions.columns import block_uniforms, py_uniform
from ..functions.objectives import Linear, SparseRows, square_norms
from ..functions.steps import StepRule

METHODS = ("full_gradient", "uniform", "sequential", "infogain", "infogain_draw", "weighted", "biased", "exact", "history", "snapshot")


@dataclass
class State:
    """What a run carries on: parameters, stored lengths, last visits."""

    w: np.ndarray
    magnitude: np.ndarray
    last_step: np.ndarray
    visits: np.ndarray
    max_weight: float = 0.0
    trace: list = field(default_factory=list)
    draws: list = field(default_factory=list)
    status: str = "running"


def probabilities(magnitude: np.ndarray, beta: float) -> np.ndarray:
    total = magnitude.sum()
    share = magnitude / total if total > 0 else np.full(len(magnitude), 1 / len(magnitude))
    return (1 - beta) * share + beta / len(magnitude)


def draw(p: np.ndarray, uniforms: np.ndarray, upto: np.ndarray | None = None) -> np.ndarray:
    """Rows whose running-sum interval holds each uniform; `upto` holds the running sums if known."""
    upto = np.cumsum(p) if upto is None else upto
    return np.minimum(np.searchsorted(upto, uniforms * upto[-1], side="right"), len(p) - 1)


class Mixture:
    """(1 - beta) * share of the lengths + beta / n, drawn and changed without a pass over all rows.

    Lengths are summed in nested groups of FAN: a draw searches the running sums of one group a
    level, a changed length renews one sum a level.  The law and the order of the rows are those of
    `probabilities` and `draw`.
    """

    FAN, TOP = 16, 8192

    def __init__(self, magnitude: np.ndarray, beta: float) -> None:
        self.n, self.beta = len(magnitude), beta
        self.levels = [self._padded(magnitude)]
        while self.levels[-1].size > self.TOP:
            self.levels.append(self._padded(self.levels[-1].sum(axis=1)))
        size = self.FAN ** (len(self.levels) - 1)
        self.rows_of_top = np.clip(self.n - np.arange(self.levels[-1].size) * size, 0, size)
        self.last_of_top = -(-self.n // size) - 1
        self.refresh()

    def _padded(self, values: np.ndarray) -> np.ndarray:
        return np.append(values, np.zeros(-len(values) % self.FAN)).reshape(-1, self.FAN)

    @property
    def magnitude(self) -> np.ndarray:
        return self.levels[0].ravel()[: self.n]

    def refresh(self) -> None:
        """The probabilities follow the lengths from here on."""
        total = self.levels[-1].sum()
        self.steep, self.flat = ((1 - self.beta) / total, self.beta / self.n) if total > 0 else (0.0, 1 / self.n)

    def put(self, rows: np.ndarray, lengths: np.ndarray) -> None:
        self.magnitude[rows] = lengths
        for k in range(1, len(self.levels)):
            rows = rows // self.FAN
            self.levels[k].ravel()[rows] = self.levels[k - 1][rows].sum(axis=1)

    def draw(self, uniforms: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows and their probabilities."""
        order = np.argsort(uniforms)  # near rows lie in near places of memory
        upto = np.cumsum(self.steep * self.levels[-1].ravel() + self.flat * self.rows_of_top)
        left = uniforms[order] * upto[-1]
        at = np.minimum(np.searchsorted(upto, left, side="right"), self.last_of_top)
        left -= np.where(at > 0, upto[at - 1], 0.0)
        each = np.arange(len(at))
        for level in range(len(self.levels) - 2, -1, -1):
            upto = np.ascontiguousarray(self.levels[level][at].T) * self.steep  # places without a row are behind all rows
            upto += self.flat * self.FAN**level
            for j in range(1, self.FAN):
                upto[j] += upto[j - 1]
            inside = np.minimum((upto <= left).sum(axis=0), self.FAN - 1)
            left -= np.where(inside > 0, upto[inside - 1, each], 0.0)
            at = at * self.FAN + inside
        rows = np.empty_like(at)
        rows[order] = np.minimum(at, self.n - 1)
        return rows, self.steep * self.magnitude[rows] + self.flat


PASS_ROWS = 1 << 16


def whole_pass(obj, w: np.ndarray, x: np.ndarray, y: np.ndarray | None, with_gradient: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """Losses and lengths of all rows and their mean gradient; what a network holds of its rows is held for PASS_ROWS of them."""
    n, losses, lengths, g = len(x), [], [], None
    for a in range(0, n, PASS_ROWS):
        few = x if n <= PASS_ROWS else x[a : a + PASS_ROWS]
        label = None if y is None else y[a : a + PASS_ROWS]
        loss, length, gradient = obj.evaluate(w, few, label)
        losses.append(loss)
        lengths.append(length)
        if with_gradient:
            part = gradient(np.full(len(few), 1 / n))
            g = part if g is None else g + part
    return np.concatenate(losses), np.concatenate(lengths), g


def greatest(value: np.ndarray, b: int) -> np.ndarray:
    """Places of the b greatest values, from the greatest on, equal ones in order; only those are sorted."""
    low = -value
    few = np.arange(len(low))
    if b < len(low):
        edge = np.partition(low, b - 1)[b - 1]
        if edge == edge:  # not when fewer than b are numbers
            few = np.flatnonzero(low <= edge)
    return few[np.argsort(low[few], kind="stable")][:b]


def variance(lengths: np.ndarray, p: np.ndarray, mean_gradient: np.ndarray) -> float:
    n = len(lengths)
    return float((lengths**2 / p).sum() / n**2 - mean_gradient @ mean_gradient)


def _entropy(p: np.ndarray) -> np.ndarray:
    q = np.clip(p, 1e-300, 1)
    r = np.clip(1 - p, 1e-300, 1)
    return -(q * np.log(q) + r * np.log(r))


class _Window:
    """Steps drawn under one set of probabilities: rows, weights and inputs, and the lengths found so far."""

    def __init__(self, rows: np.ndarray, prob: np.ndarray | None, n: int = 0) -> None:
        self.rows, self.prob, self.at, self.written = rows, prob, 0, 0
        self.weight = None if prob is None else 1 / (n * prob)
        self.most = None if prob is None else self.weight.max(axis=1).tolist()
        self.scale = (np.ones(rows.shape) if prob is None else self.weight) / rows.shape[1]
        self.x = self.y = self.norm = None
        self.lengths: list[np.ndarray] = []

    def take(self, x: np.ndarray, y: np.ndarray | None, with_norms: bool) -> None:
        self.x, self.y = x[self.rows], None if y is None else y[self.rows]
        self.norm = np.sqrt((self.x * self.x).sum(axis=2)) if with_norms else None

    def write(self, s: State, tree: Mixture | None, t: int) -> None:
        """Lengths, last steps and visits up to step t; nothing reads them before the next draw or look."""
        rows = self.rows[self.written : self.at]
        if not len(rows):
            return
        lengths = np.array(self.lengths) if self.norm is None else np.abs(self.lengths) * self.norm[self.written : self.at]
        own, lengths = rows.ravel(), lengths.ravel()  # of a row that was drawn again the last length stays
        if tree is None:
            s.magnitude[own] = lengths
        else:
            tree.put(own, lengths)
        s.last_step[own] = np.repeat(np.arange(t - len(rows) + 1, t + 1), rows.shape[1])
        np.add.at(s.visits, own, 1)
        self.written, self.lengths = self.at, []


TREE_ROWS = 1 << 15  # of more rows the sums of lengths are kept, not made again at each redraw
AHEAD = 8  # steps of uniform draws whose rows are taken together
UNIFORMS = 1 << 16


def run_steps(obj, x: np.ndarray, y: np.ndarray | None, w: np.ndarray, *, method: str = "uniform", steps: int, batch: int = 128, rule: StepRule, seed: int = 0, beta: float = 0.2, floor: float = 0.0, magnitude: np.ndarray | None = None, prob: np.ndarray | None = None, anchor: np.ndarray | None = None, gamma: float = 0.0, first_step: int = 0, refresh: str = "pre", rescan_every: int = 0, redraw_every: int = 1, replacement: bool = True, gain: str = "entropy", snapshot_every: int = 100, eval_every: int = 0, x_valid: np.ndarray | None = None, y_valid: np.ndarray | None = None, measure_variance: bool = False, stop_error: float | None = None, keep_draws: bool = False, prox: bool = False, stage: int = 0) -> State:
    """`steps` steps of one method from parameters `w`.

    anchor and gamma add (gamma / 2) * |anchor - w|^2, the pull of a stage towards where it began.
    redraw_every > 1 keeps the drawing probabilities for that many steps (prefetched draws); the
    weights use the probabilities of the draw, so the gradient stays unbiased.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method}")
    if method == "history" and not 0 < beta <= 1:
        raise ValueError("beta must be in (0, 1]; at 0 rows can starve")
    n = len(x)
    pick = lambda i: None if y is None else y[i]
    s = State(w.copy(), np.ones(n) if magnitude is None else magnitude.astype(float).copy(), np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64))
    p, upto, tree = np.full(n, 1 / n), None, None  # running sums of p, until p changes; sums of lengths of many rows
    sparse = isinstance(x, SparseRows)
    plain = isinstance(obj, Linear) and not sparse and refresh == "pre"
    ahead = method == "history" or (method == "uniform" and replacement)
    window = redraw_every if method == "history" else AHEAD
    penalty = None if prox or obj.penalty.kind == "none" else obj.penalty
    ready, ready_from, now = np.zeros((0, batch)), 0, None
    snapshot, snapshot_gradient = s.w, None

    def uniforms(t: int, many: int) -> np.ndarray:
        """Those of `many` steps from t on; some thousands are made at a time."""
        nonlocal ready, ready_from
        if t + many > ready_from + len(ready):
            ready, ready_from = block_uniforms(seed, t, max(many, min(UNIFORMS // batch, first_step + steps + 1 - t)), batch), t
        return ready[t - ready_from : t - ready_from + many]

    began, spent = time.perf_counter(), 0.0
    for k in range(1, steps + 1):
        t = first_step + k
        weight = scale = None
        if ahead:
            if now is None or now.at == len(now.rows):
                if now is not None:
                    now.write(s, tree, t - 1)
                u = uniforms(t, min(window, steps + 1 - k))
                if method == "uniform":
                    now = _Window(np.minimum((u * n).astype(np.int64), n - 1), None)
                else:
                    if rescan_every and (k - 1) % rescan_every == 0:
                        s.magnitude, tree = obj.evaluate(s.w, x, y)[1], None
                    if n > TREE_ROWS:
                        tree = Mixture(s.magnitude, beta) if tree is None else tree
                        s.magnitude = tree.magnitude
                        tree.refresh()
                        rows, prob = tree.draw(u.ravel())
                    else:
                        p = probabilities(s.magnitude, beta)
                        rows = draw(p, u.ravel())
                        prob = p[rows]
                    now = _Window(rows.reshape(u.shape), prob.reshape(u.shape), n)
                if not sparse:
                    now.take(x, y, plain)
            i, now.at = now.at, now.at + 1
            rows, scale = now.rows[i], now.scale[i]
            weight = None if now.weight is None else now.weight[i]
            own = (x[rows], pick(rows)) if sparse else (now.x[i], None if y is None else now.y[i])
        elif method == "full_gradient":
            rows = np.arange(n)
        elif method == "sequential":
            rows = (np.arange(batch) + (t - 1) * batch) % n
        elif method == "snapshot":
            rows = np.minimum((uniforms(t, 1)[0] * n).astype(np.int64), n - 1)
        elif method == "uniform":
            rows = np.argsort([py_uniform(seed, t, "r", i) for i in range(n)])[:batch]
        elif method in ("infogain", "infogain_draw"):
            score = x @ s.w
            q = 1 / (1 + np.exp(-np.clip(score, -500, 500)))
            value = (_entropy(q) if gain == "entropy" else 2 * q * (1 - q)) * np.sqrt(square_norms(x))
            if method == "infogain":
                value = value * (t - s.last_step)
                rows = greatest(value, batch)
            else:
                p = probabilities(value, floor)
                rows = draw(p, uniforms(t, 1)[0])
                weight = 1 / (n * p[rows])
        else:
            if method == "exact":
                p, upto = probabilities(obj.evaluate(s.w, x, y)[1], floor), None
            else:
                p = prob / prob.sum()
            upto = np.cumsum(p) if upto is None else upto
            rows = draw(p, uniforms(t, 1)[0], upto)
            weight = None if method == "biased" else 1 / (n * p[rows])
        if not ahead:
            own = x[rows], pick(rows)
            scale = np.full(len(rows), 1 / len(rows)) if weight is None else weight / len(rows)
        if ahead and plain:
            lengths = obj.slope(own[0] @ s.w, own[1])  # times the rows' norms when written
            g = own[0].T @ (lengths * scale)
        else:
            _, lengths, gradient = obj.evaluate(s.w, *own)
            g = gradient(scale)
        if method == "snapshot":
            if snapshot_gradient is None or (k - 1) % snapshot_every == 0:
                snapshot = s.w.copy()
                snapshot_gradient = obj.evaluate(snapshot, x, y)[2](np.full(n, 1 / n))
            g = g - obj.evaluate(snapshot, *own)[2](scale) + snapshot_gradient
        if weight is not None:
            s.max_weight = max(s.max_weight, now.most[i] if ahead else float(weight.max()))
        if penalty is not None:
            g = g + penalty.gradient(s.w)
        if anchor is not None and gamma:
            g = g + gamma * (s.w - anchor)
        s.w = s.w - rule.move(g, t)
        if prox and obj.penalty.kind == "l1":
            s.w = obj.penalty.shrink(s.w, rule.rate(t))
        if refresh == "post":
            lengths = obj.evaluate(s.w, *own)[1]
        if ahead:
            now.lengths.append(lengths)
        else:
            s.magnitude[rows] = lengths  # repeated rows of a batch have one length
            s.last_step[rows] = t
            np.add.at(s.visits, rows, 1)
        if keep_draws:
            chance = now.prob[i] if weight is not None and ahead else p[rows]
            s.draws += [(t, j, int(r), float(chance[j]), 1.0 if weight is None else float(weight[j])) for j, r in enumerate(rows.tolist())]
        if eval_every and (k % eval_every == 0 or k == steps):
            if ahead:
                now.write(s, tree, t)
            spent += time.perf_counter() - began
            s.trace.append(_look(obj, x, y, x_valid, y_valid, s, t, spent, method, beta, p, stage, measure_variance))
            began = time.perf_counter()
            if stop_error is not None and s.trace[-1]["error"] <= stop_error:
                s.status = "reached"
                break
            if not math.isfinite(s.trace[-1]["loss"]):
                s.status = "diverged"
                break
    if now is not None:
        now.write(s, tree, t)
    return s


def _look(obj, x, y, xv, yv, s: State, t: int, spent: float, method: str, beta: float, p: np.ndarray, stage: int, with_variance: bool) -> dict:
    """One trace row: objective on the training rows, error on held-out rows, variance ratio."""
    varied = with_variance and method not in ("full_gradient", "sequential", "infogain")
    losses, lengths, g = whole_pass(obj, s.w, x, y, varied)
    wrong = obj.wrong(s.w, x if xv is None else xv, y if xv is None else yv)
    ratio = 1.0
    if varied:
        n = len(x)
        flat = variance(lengths, np.full(n, 1 / n), g)
        now = probabilities(s.magnitude, beta) if method == "history" else probabilities(lengths, 0.0) if method == "exact" else p
        usable = np.where(now > 0, now, np.inf)
        ratio = variance(lengths, usable, g) / flat if flat > 1e-15 else 1.0
    return {"step": t, "stage": stage, "loss": float(losses.mean()), "penalty": obj.penalty.value(s.w), "error": float(wrong.mean()), "nonzero": int(np.count_nonzero(np.abs(s.w) > 1e-8)), "var_ratio": float(ratio), "max_weight": float(s.max_weight), "elapsed_s": spent}
