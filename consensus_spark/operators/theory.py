"""Bounds and rates of the convergence analysis."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def smoothness(gram: np.ndarray, model: str = "softmax") -> float:
    """Largest eigenvalue of the second-moment matrix, halved for cross-entropy."""
    top = float(np.linalg.eigvalsh(gram)[-1])
    return top / 2 if model == "softmax" else top


def _log_shrink(n: int, b: int, beta: float) -> float:
    """log(1 - beta^(nb)) without losing a tiny power."""
    return math.log1p(-math.exp(n * b * math.log(beta)))


def min_iterations_for_bound(n: int, b: int, beta: float, tol: float) -> float:
    """Iterations from which the gradient bound is claimed."""
    return (n * b * math.log(tol) / _log_shrink(n, b, beta) + n * b + 2) / 2


def gradient_bound(k: int, gap: float, step: float, lipschitz: float, n: int, b: int, beta: float, variance: float) -> float:
    """Right side of the gradient bound; large factors are combined as logarithms."""
    nb = n * b
    shrink = _log_shrink(n, b, beta)
    root = -math.expm1(-shrink / nb)  # 1 - (1 - beta^nb)^(-1/nb)
    log_lead = 2 * math.log1p(math.exp(-nb * math.log(beta))) if -nb * math.log(beta) < 700 else -2 * nb * math.log(beta)
    log_alpha = (
        math.log(4 * step**2 * lipschitz**3 * n) + log_lead + (2 * k - nb - 2) / nb * shrink - 2 * math.log(abs(root))
    )
    spread = math.exp(log_alpha) if log_alpha < 700 else math.inf
    return 2 * abs(gap) / (step * k) + (spread + lipschitz * step / n) * variance


def loss_gap_bound(
    k: Column, distance2: float | Column, step: float, lipschitz: float, n: int, variance: float | Column, variance_power: int = 2
) -> Column:
    """Right side of the loss-gap bound; the variance term carries step^2 (or step^1)."""
    return F.lit(distance2) / (2 * step * k) + lipschitz * step**variance_power / (2 * n) * variance


def iterations_required(tol: Column, n: Column) -> Column:
    """Order of iterations to a loss tolerance: 1 / (tol^2 N)."""
    return F.ceil(1 / (tol * tol * n)).cast("long")


def rate_fit(history: DataFrame) -> DataFrame:
    """Slope of log gap against log(N K)."""
    return history.filter("gap > 0").agg(F.regr_slope(F.log("gap"), F.log(F.col("n") * F.col("k"))).alias("slope"))


def speedup(required: dict[int, int]) -> list[tuple[int, int, float]]:
    """(N, iterations, iterations of the smallest N over it)."""
    base = required[min(required)]
    return [(n, k, base / k) for n, k in sorted(required.items())]
