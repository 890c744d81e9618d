"""The mixing-only phase, the shadow mean and the closed expansion."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from consensus_spark.operators.mixing import mix
from consensus_spark.operators.quality import worker_losses


def collapse(matrices: list[np.ndarray], tol: float, spread: float = 1.0) -> tuple[np.ndarray, int]:
    """Product of matrices until columns agree within ``tol``, and how many were used."""
    product, used = np.eye(len(matrices[0])), 0
    for m in matrices:
        if spread * np.ptp(product, axis=1).max() <= tol:
            break
        product, used = product @ m, used + 1
    return product, used


def consensus_phase(spark: SparkSession, params: DataFrame, matrices: list[np.ndarray], tol: float = 1e-9) -> tuple[DataFrame, int]:
    """Keep mixing without gradients: one job, whatever the number of iterations."""
    product, used = collapse(matrices, tol)
    n = len(product)
    w = spark.createDataFrame(
        [(i, j, float(product[i, j])) for i in range(n) for j in range(n)], "src int, dst int, w double"
    )
    return mix(params, w), used


def mean_iterate(start: np.ndarray, grads: list[np.ndarray], steps: list[float]) -> np.ndarray:
    """Mean start minus accumulated mean gradients (rows are workers)."""
    return start.mean(axis=0) - sum(s * g.mean(axis=0) for s, g in zip(steps, grads, strict=True))


def unrolled(start: np.ndarray, grads: list[np.ndarray], steps: list[float], mats: list[np.ndarray]) -> np.ndarray:
    """Closed expansion of the recursion: every gradient carried by the products after it."""
    out = np.linalg.multi_dot([start.T, *mats]) if mats else start.T
    for i, (g, s) in enumerate(zip(grads, steps, strict=True)):
        tail = np.eye(len(start))
        for m in mats[i:]:
            tail = tail @ m
        out = out - s * g.T @ tail
    return out.T


def output_model(params: DataFrame, how: str = "mean", worker: int = 0) -> DataFrame:
    if how == "mean":
        return params.groupBy("idx").agg(F.avg("val").alias("val"))
    return params.filter(F.col("worker") == worker).select("idx", "val")


def best_worker(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    """The parameters of the worker whose own model has the least loss (ties: the first)."""
    losses = worker_losses(ex, params, model).select(F.struct(F.round("loss", 9).alias("loss"), "owner").alias("o"))
    one = losses.agg(F.min("o").getField("owner").alias("_best"))
    return params.join(F.broadcast(one), F.col("worker") == F.col("_best")).drop("_best")


def iterations_to_agree(start: np.ndarray, mats, tols: list[float], whole: bool = False) -> tuple[list[tuple[int, float, float]], dict[float, int]]:
    """Mixing alone: (iteration, largest squared distance to the mean, drift of the mean) along the
    phase, and the iterations that each tolerance takes.  It ends with the last tolerance, or with
    ``whole`` after all matrices."""
    w, mean, rows, first = start.copy(), start.mean(axis=0), [], {}
    for used, m in enumerate(mats, 1):
        w = m.T @ w
        spread = float(((w - w.mean(axis=0)) ** 2).sum(axis=1).max())
        rows.append((used, spread, float(np.abs(w.mean(axis=0) - mean).max())))
        first |= {t: used for t in tols if spread <= t and t not in first}
        if len(first) == len(tols) and not whole:
            break
    return rows, first
