"""Objectives on NumPy batches: losses, gradients and per-row gradient lengths.

Parameters are one flat vector, so step rules and penalties need no shapes.  Every objective has
`evaluate(w, x, y)`, which returns the rows' losses, the lengths of the rows' gradients and a
function that sums the rows' gradients under given weights.  Lengths come from row norms of
what the backward pass holds anyway, never from per-row gradient matrices, and are
taken before any weight is applied.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np

Evaluated = tuple[np.ndarray, np.ndarray, Callable[[np.ndarray], np.ndarray]]


def stable_sigmoid(z: np.ndarray) -> np.ndarray:
    small = np.exp(-np.abs(z))
    return np.where(z >= 0, 1.0, small) / (1 + small)


class SparseRows:
    """Rows of which only the places with values are held; what a linear objective needs of a matrix."""

    def __init__(self, edges: np.ndarray, places: np.ndarray, values: np.ndarray) -> None:
        self.edges, self.places, self.values = edges, places, values
        self.row = np.repeat(np.arange(len(edges) - 1), np.diff(edges))

    @classmethod
    def of(cls, places: list, values: list) -> SparseRows:
        sizes = [len(p) for p in places]
        flat = lambda parts, kind: np.concatenate([np.asarray(p, dtype=kind) for p in parts]) if sum(sizes) else np.zeros(0, kind)
        return cls(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64), flat(places, np.int64), flat(values, np.float64))

    def __len__(self) -> int:
        return len(self.edges) - 1

    def __getitem__(self, rows: np.ndarray) -> SparseRows:
        rows = np.arange(len(self))[rows]
        size = (self.edges[1:] - self.edges[:-1])[rows]
        edges = np.concatenate([[0], np.cumsum(size)])
        at = np.repeat(self.edges[:-1][rows] - edges[:-1], size) + np.arange(int(edges[-1]))
        return SparseRows(edges, self.places[at], self.values[at])

    def __matmul__(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, self.values * w[self.places], len(self))


def square_norms(x: np.ndarray | SparseRows) -> np.ndarray:
    return np.bincount(x.row, x.values**2, len(x)) if isinstance(x, SparseRows) else (x * x).sum(axis=1)


def weighted_sum(x: np.ndarray | SparseRows, weight: np.ndarray, dim: int) -> np.ndarray:
    """Sum of the rows under weights."""
    return np.bincount(x.places, x.values * weight[x.row], dim) if isinstance(x, SparseRows) else x.T @ weight


@dataclass
class Penalty:
    """none, l2 (lam * |w|^2) or l1 (lam * sum |w|); never part of the sampling."""

    kind: str = "none"
    lam: float = 0.0

    def value(self, w: np.ndarray) -> float:
        return {"none": 0.0, "l2": self.lam * float(w @ w), "l1": self.lam * float(np.abs(w).sum())}[self.kind]

    def gradient(self, w: np.ndarray) -> np.ndarray:
        return {"none": 0.0 * w, "l2": 2 * self.lam * w, "l1": self.lam * np.sign(w)}[self.kind]

    def shrink(self, w: np.ndarray, eta: float) -> np.ndarray:
        """Soft threshold: the proximal form of l1."""
        return np.sign(w) * np.maximum(np.abs(w) - eta * self.lam, 0.0)


@dataclass
class Linear:
    """Squared, hinge or logistic loss of a linear score; rows are dense or SparseRows."""

    kind: str
    dim: int
    penalty: Penalty = field(default_factory=Penalty)

    def start(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.dim)

    def slope(self, s: np.ndarray, y: np.ndarray) -> np.ndarray:
        """Derivative of the loss in the score: all that a step needs of a row beside its features."""
        if self.kind == "squared":
            return 2 * (s - y)
        if self.kind == "hinge":
            return np.where(s * y < 1, -y, 0.0)
        if self.kind == "logistic":
            return -y * stable_sigmoid(-(s * y))
        raise ValueError(self.kind)

    def evaluate(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> Evaluated:
        s = x @ w
        m, slope = s * y, self.slope(s, y)
        if self.kind == "squared":
            losses = (s - y) ** 2
        elif self.kind == "hinge":
            losses = np.maximum(0, 1 - m)
        else:
            losses = np.log1p(np.exp(-np.abs(m))) + np.maximum(-m, 0)
        return losses, np.abs(slope) * np.sqrt(square_norms(x)), lambda weight: weighted_sum(x, slope * weight, self.dim)

    def wrong(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return np.where(x @ w >= 0, 1.0, -1.0) != y


@dataclass
class Mlp:
    """Dense layers with one activation and a soft-max loss; sizes = (inputs, ..., classes).

    Two sizes make plain multi-class soft-max regression.
    """

    sizes: tuple[int, ...]
    activation: str = "tanh"
    penalty: Penalty = field(default_factory=Penalty)
    include_bias: bool = False

    def start(self, seed: int = 0) -> np.ndarray:
        rng = np.random.default_rng(seed)
        return np.concatenate([np.concatenate([(rng.standard_normal((m, n)) / np.sqrt(n)).ravel(), np.zeros(m)]) for n, m in zip(self.sizes, self.sizes[1:], strict=False)])

    def layers(self, w: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        out, at = [], 0
        for n, m in zip(self.sizes, self.sizes[1:], strict=False):
            out.append((w[at : at + n * m].reshape(m, n), w[at + n * m : at + n * m + m]))
            at += n * m + m
        return out

    def _act(self, z: np.ndarray) -> np.ndarray:
        return {"tanh": np.tanh, "relu": lambda v: np.maximum(v, 0), "sigmoid": stable_sigmoid, "identity": lambda v: v}[self.activation](z)

    def _act_slope(self, h: np.ndarray) -> np.ndarray:
        return {"tanh": lambda v: 1 - v * v, "relu": lambda v: (v > 0).astype(float), "sigmoid": lambda v: v * (1 - v), "identity": np.ones_like}[self.activation](h)

    def forward(self, w: np.ndarray, x: np.ndarray) -> list[np.ndarray]:
        """Inputs of every layer, then the scores."""
        held, layers = [x], self.layers(w)
        for k, (a, b) in enumerate(layers):
            z = held[-1] @ a.T + b
            held.append(z if k == len(layers) - 1 else self._act(z))
        return held

    def deltas(self, w: np.ndarray, held: list[np.ndarray], y: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """Losses, and the loss derivative at every layer's sums, last layer first."""
        z = held[-1] - held[-1].max(axis=1, keepdims=True)
        p = np.exp(z)
        p /= p.sum(axis=1, keepdims=True)
        rows = np.arange(len(y))
        losses = -np.log(np.maximum(p[rows, y.astype(int)], 1e-300))
        p[rows, y.astype(int)] -= 1
        out, layers = [p], self.layers(w)
        for k in range(len(layers) - 1, 0, -1):
            out.append((out[-1] @ layers[k][0]) * self._act_slope(held[k]))
        return losses, out

    def evaluate(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> Evaluated:
        held = self.forward(w, x)
        losses, deltas = self.deltas(w, held, y)
        pairs = list(zip(held[:-1], reversed(deltas), strict=True))
        squared = sum((d * d).sum(axis=1) * ((h * h).sum(axis=1) + self.include_bias) for h, d in pairs)

        def gradient(weight: np.ndarray) -> np.ndarray:
            parts = []
            for h, d in pairs:
                scaled = d * weight[:, None]
                parts += [(scaled.T @ h).ravel(), scaled.sum(axis=0)]
            return np.concatenate(parts)

        return losses, np.sqrt(squared), gradient

    def wrong(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self.forward(w, x)[-1].argmax(axis=1) != y


@dataclass
class Pca:
    """Squared error of projecting a row on `rank` directions and back; no label."""

    dim: int
    rank: int
    penalty: Penalty = field(default_factory=Penalty)

    def start(self, seed: int = 0) -> np.ndarray:
        return np.linalg.qr(np.random.default_rng(seed).standard_normal((self.dim, self.rank)))[0].ravel()

    def evaluate(self, w: np.ndarray, x: np.ndarray, y: np.ndarray | None) -> Evaluated:
        m = w.reshape(self.dim, self.rank)
        a = x @ m
        r = a @ m.T - x
        c = r @ m
        dot = lambda u, v: (u * v).sum(axis=1)
        squared = 4 * (dot(r, r) * dot(a, a) + dot(x, x) * dot(c, c) + 2 * dot(r, x) * dot(a, c))
        return dot(r, r), np.sqrt(np.maximum(squared, 0)), lambda weight: 2 * ((r * weight[:, None]).T @ a + (x * weight[:, None]).T @ c).ravel()

    def wrong(self, w: np.ndarray, x: np.ndarray, y: np.ndarray | None) -> np.ndarray:
        return np.zeros(len(x), dtype=bool)


def fourier_features(x: np.ndarray, dim: int, width: float, seed: int) -> np.ndarray:
    """Random features whose products approach a Gaussian kernel of the given width."""
    rng = np.random.default_rng(seed)
    return np.sqrt(2 / dim) * np.cos(x @ (rng.standard_normal((x.shape[1], dim)) / width) + rng.uniform(0, 2 * np.pi, dim))


def outer_lengths(obj, w: np.ndarray, x: np.ndarray, y: np.ndarray, weights_only: bool = False) -> np.ndarray:
    """Gradient lengths row by row, by brute force: one gradient for each row."""
    out = []
    for i in range(len(x)):
        g = obj.evaluate(w, x[i : i + 1], None if y is None else y[i : i + 1])[2](np.ones(1))
        if weights_only and isinstance(obj, Mlp):
            g = np.concatenate([a.ravel() for a, _ in obj.layers(g)])
        out.append(float(np.sqrt(g @ g)))
    return np.array(out)
