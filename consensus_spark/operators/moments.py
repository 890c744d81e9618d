"""Least squares by second moments: one pass over the data, any number of iterations.

A mini-batch enters least squares only through its moments, so the batches of a whole run
are summed once (one row per batch, however large the table) and every run over them, of
any policy, step or number of workers, costs no further scan.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Moments held on the driver, checked before they are fetched.
MOST_BYTES = 64 << 20


def batch_moments(ex: DataFrame, width: int) -> DataFrame:
    """``batch``, ``n``, ``yy`` and the sums ``m``: x_i x_j for i <= j, then x_i y."""
    x = lambda i: F.get("x", F.lit(i))
    sums = [F.sum(x(i) * x(j)) for i in range(width) for j in range(i, width)] + [F.sum(x(i) * F.col("y")) for i in range(width)]
    wide = ex.groupBy("batch").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("y") * F.col("y")).alias("yy"), *[s.alias(f"_{i}") for i, s in enumerate(sums)])
    return wide.select("batch", "n", "yy", F.array(*[f"_{i}" for i in range(len(sums))]).alias("m"))


@dataclass
class Moments:
    """Per batch: rows, Gram sums, target sums and squared targets."""

    n: np.ndarray
    gram: np.ndarray
    xy: np.ndarray
    yy: np.ndarray

    @staticmethod
    def fetch(table: DataFrame, count: int, width: int) -> Moments:
        if count * (width * width + width + 2) * 8 > MOST_BYTES:
            raise ValueError("too many batches for the driver")
        n, yy = np.zeros((2, count))
        gram, xy = np.zeros((count, width, width)), np.zeros((count, width))
        upper = np.triu_indices(width)
        for r in table.collect():
            b, m = r["batch"], np.array(r["m"])
            n[b], yy[b] = r["n"], r["yy"]
            gram[b][upper] = m[: len(upper[0])]
            gram[b] = np.triu(gram[b]) + np.triu(gram[b], 1).T
            xy[b] = m[len(upper[0]) :]
        return Moments(n, gram, xy, yy)

    def gradient(self, b: int, w: np.ndarray) -> np.ndarray:
        return (self.gram[b] @ w - self.xy[b]) / max(self.n[b], 1)

    def whole(self) -> tuple[np.ndarray, np.ndarray, float]:
        n = self.n.sum()
        return self.gram.sum(axis=0) / n, self.xy.sum(axis=0) / n, float(self.yy.sum() / n)

    def loss(self, w: np.ndarray) -> float:
        g, xy, yy = self.whole()
        return float(0.5 * (yy - 2 * w @ xy + w @ g @ w))

    def best(self) -> np.ndarray:
        g, xy, _ = self.whole()
        return np.linalg.solve(g, xy)


def synchronous(m: Moments, n: int, last: int, step: float, mats: dict[int, np.ndarray] | np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(k, parameters): iteration k gives worker i batch (k - 1) n + i, so batches are alike for any n."""
    w = np.zeros((n, m.xy.shape[1]))
    for k in range(1, last + 1):
        g = np.array([m.gradient(((k - 1) * n + i) % len(m.n), w[i]) for i in range(n)])
        mat = mats[k] if isinstance(mats, dict) else mats
        w = mat.T @ (w - step * g)
        yield k, w


def asynchronous(m: Moments, arrivals: list[tuple[int, int]], n: int, step: float) -> Iterator[tuple[int, int, np.ndarray]]:
    """(update, its staleness, server parameters): a server applies each gradient on arrival.

    ``arrivals``: (worker, that worker's count so far) in order.  A worker reads the server
    after its update and computes its next gradient there.
    """
    w = np.zeros(m.xy.shape[1])
    read = [(0, w)] * n
    for at, (i, k) in enumerate(arrivals, 1):
        seen, own = read[i]
        w = w - step * m.gradient(((k - 1) * n + i) % len(m.n), own)
        read[i] = (at, w)
        yield at, at - 1 - seen, w


def bounded_staleness(m: Moments, times: Iterator[tuple[int, list[float]]], n: int, bound: int, step: float):
    """(k, clock, parameters): nobody starts iteration k + bound + 1 before all have ended k.

    A gradient of iteration k is taken at the parameters the server had when its worker
    began; updates that ended by then are in it.
    """
    finish, w = [[0.0] * n], np.zeros(m.xy.shape[1])
    done: list[tuple[float, np.ndarray]] = []  # updates not yet seen by every worker
    base = w.copy()
    for k, t in times:
        gate = max(finish[max(0, len(finish) - 1 - bound)])
        began = [max(finish[-1][i], gate) for i in range(n)]
        ended = [b + t[i] for i, b in enumerate(began)]
        for i in range(n):
            view = base + sum((u for e, u in done if e <= began[i]), np.zeros_like(base))
            done.append((ended[i], -step / n * m.gradient(((k - 1) * n + i) % len(m.n), view)))
        finish.append(ended)
        del finish[: -bound - 1]
        low = min(ended)
        base = base + sum((u for e, u in done if e <= low), np.zeros_like(base))
        done = [(e, u) for e, u in done if e > low]
        yield k, max(ended), base + sum((u for _, u in done), np.zeros_like(base))
