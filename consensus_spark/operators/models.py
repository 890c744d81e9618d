"""Models: numpy kernels over batches, and column forms of the linear ones."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from consensus_spark.functions.vectors import dot, let, log_sum_exp, logits, softmax


@dataclass(frozen=True)
class Softmax:
    """Multinomial logistic regression; the last feature is the constant."""

    n_features: int
    n_classes: int
    l2: float = 0.0

    @property
    def size(self) -> int:
        return self.n_features * self.n_classes

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def _scores(self, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        return x @ w.reshape(self.n_classes, self.n_features).T

    def loss_sum(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> float:
        z = self._scores(w, x)
        top = z.max(axis=1)
        return float((top + np.log(np.exp(z - top[:, None]).sum(axis=1)) - z[np.arange(len(y)), y]).sum())

    def grad_sum(self, w: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        z = self._scores(w, x)
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        p[np.arange(len(y)), y] -= 1.0
        return (p.T @ x).ravel()

    def predict(self, w: np.ndarray, x: np.ndarray) -> np.ndarray:
        return self._scores(w, x).argmax(axis=1)

    def grad_column(self, w: Column, x: Column, y: Column) -> Column:
        """Flat gradient of one row."""
        delta = F.transform(softmax(logits(w, x, self.n_features, self.n_classes)), lambda p, c: p - (c == y).cast("double"))
        return let(delta, lambda d: F.flatten(F.transform(d, lambda e: F.transform(x, lambda v: e * v))))

    def loss_column(self, w: Column, x: Column, y: Column) -> Column:
        z = logits(w, x, self.n_features, self.n_classes)
        return let(z, lambda v: log_sum_exp(v) - F.element_at(v, y + 1))


@dataclass(frozen=True)
class LeastSquares:
    """Half squared error; the optimum is known in closed form."""

    n_features: int
    l2: float = 0.0

    @property
    def size(self) -> int:
        return self.n_features

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(self.size)

    def loss_sum(self, w, x, y) -> float:
        return float(0.5 * ((x @ w - y) ** 2).sum())

    def grad_sum(self, w, x, y) -> np.ndarray:
        return x.T @ (x @ w - y)

    def predict(self, w, x) -> np.ndarray:
        return x @ w

    def grad_column(self, w: Column, x: Column, y: Column) -> Column:
        return let(dot(w, x) - y, lambda e: F.transform(x, lambda v: e * v))

    def loss_column(self, w: Column, x: Column, y: Column) -> Column:
        return let(dot(w, x) - y, lambda e: 0.5 * e * e)


@dataclass(frozen=True)
class Quadratic:
    """Mean of (w - y)^2 / 2 over scalars: hand examples."""

    @property
    def size(self) -> int:
        return 1

    def init(self, seed: int = 0) -> np.ndarray:
        return np.zeros(1)

    def loss_sum(self, w, x, y) -> float:
        return float(0.5 * ((w[0] - y) ** 2).sum())

    def grad_sum(self, w, x, y) -> np.ndarray:
        return np.array([float((w[0] - y).sum())])

    def predict(self, w, x) -> np.ndarray:
        return np.full(len(x), w[0])


@dataclass(frozen=True)
class Mlp:
    """Two hidden layers of rectified units under cross-entropy; kernels only."""

    n_features: int
    n_classes: int
    hidden: tuple[int, int] = (64, 32)
    l2: float = 0.0

    def _shapes(self):
        sizes = [self.n_features, *self.hidden, self.n_classes]
        return [((a, b), (b,)) for a, b in zip(sizes, sizes[1:], strict=False)]

    @property
    def size(self) -> int:
        return sum(a * b + b for (a, b), _ in self._shapes())

    def init(self, seed: int = 0) -> np.ndarray:
        rng = np.random.default_rng(seed)
        parts = []
        for (a, b), _ in self._shapes():
            parts += [rng.normal(0, np.sqrt(2 / a), a * b), np.zeros(b)]
        return np.concatenate(parts)

    def _layers(self, w: np.ndarray):
        at, out = 0, []
        for (a, b), _ in self._shapes():
            out.append((w[at : at + a * b].reshape(a, b), w[at + a * b : at + a * b + b]))
            at += a * b + b
        return out

    def _forward(self, w, x):
        acts, layers = [x], self._layers(w)
        for i, (m, b) in enumerate(layers):
            z = acts[-1] @ m + b
            acts.append(np.maximum(z, 0) if i + 1 < len(layers) else z)
        return acts, layers

    def loss_sum(self, w, x, y) -> float:
        z = self._forward(w, x)[0][-1]
        top = z.max(axis=1)
        return float((top + np.log(np.exp(z - top[:, None]).sum(axis=1)) - z[np.arange(len(y)), y]).sum())

    def grad_sum(self, w, x, y) -> np.ndarray:
        acts, layers = self._forward(w, x)
        z = acts[-1]
        d = np.exp(z - z.max(axis=1, keepdims=True))
        d /= d.sum(axis=1, keepdims=True)
        d[np.arange(len(y)), y] -= 1.0
        out: list[np.ndarray] = []
        for i in range(len(layers) - 1, -1, -1):
            out = [(acts[i].T @ d).ravel(), d.sum(axis=0), *out]
            d = (d @ layers[i][0].T) * (acts[i] > 0)
        return np.concatenate(out)

    def predict(self, w, x) -> np.ndarray:
        return self._forward(w, x)[0][-1].argmax(axis=1)


def regulariser(w: np.ndarray, l2: float = 0.0, l1: float = 0.0) -> tuple[float, np.ndarray]:
    """Value and (sub)gradient of l2/2 |w|^2 + l1 |w|_1."""
    return float(l2 / 2 * w @ w + l1 * np.abs(w).sum()), l2 * w + l1 * np.sign(w)


def least_squares_optimum(gram: np.ndarray, xy: np.ndarray, l2: float = 0.0) -> np.ndarray:
    return np.linalg.solve(gram + l2 * np.eye(len(gram)), xy)
