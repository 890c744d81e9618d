"""Gradient steps and mixing in relational form.

Parameters are rows (worker, idx, val), so a run's state can be partitioned by
``idx``; mixing acts on the worker axis alone and a small weight table is joined in.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def equal_start(spark: SparkSession, n: int, values: list[float]) -> DataFrame:
    """The same parameters at every worker."""
    flat = F.array(*[F.lit(float(v)) for v in values])
    return spark.range(n).select(F.col("id").cast("int").alias("worker"), F.posexplode(flat).alias("idx", "val"))


#: Parameters are broadcast up to so many bytes; more are joined by place.
BROADCAST_BYTES = 64 << 20
#: A gradient of so many places is summed as that many columns of one aggregate.
WIDE = 256


def packed(params: DataFrame) -> DataFrame:
    """One array per worker."""
    a = F.array_sort(F.collect_list(F.struct("idx", "val")))
    return params.groupBy("worker").agg(F.transform(a, lambda p: p["val"]).alias("w"))


def local_gradient(batch: DataFrame, params: DataFrame, model, n: int = 64) -> DataFrame:
    """Mean gradient of each worker at its own parameters: (worker, idx, g).

    The parameters of all ``n`` workers are broadcast if N x d doubles fit; sums combine
    before the shuffle, so a task sends one row per worker (or per worker and place).
    """
    if n * model.size * 8 > BROADCAST_BYTES:
        return long_gradient(batch, params, model)
    own = batch.join(F.broadcast(packed(params)), "worker")
    rows = own.select("worker", model.grad_column(F.col("w"), F.col("x"), F.col("y")).alias("g"))
    if model.size > WIDE:
        long = rows.select("worker", F.posexplode("g").alias("idx", "g"))
        return long.groupBy("worker", "idx").agg(F.avg("g").alias("g"))
    wide = rows.groupBy("worker").agg(*[F.avg(F.get("g", F.lit(i))).alias(f"g{i}") for i in range(model.size)])
    return wide.select("worker", F.posexplode(F.array(*[f"g{i}" for i in range(model.size)])).alias("idx", "g"))


def long_gradient(batch: DataFrame, params: DataFrame, model) -> DataFrame:
    """The same with parameters joined by worker and feature: nothing grows with d in one row.

    For models that are linear in the features (softmax, least squares).
    """
    width, classes = model.n_features, getattr(model, "n_classes", 1)
    rows = batch.select("row_id", "worker", "y", F.posexplode("x").alias("f", "v"))
    at = params.select("worker", (F.col("idx") % width).alias("f"), F.floor(F.col("idx") / width).cast("int").alias("c"), "val")
    score = rows.join(at, ["worker", "f"]).groupBy("worker", "row_id", "y", "c").agg(F.sum(F.col("v") * F.col("val")).alias("z"))
    if classes > 1:
        e = F.array_sort(F.collect_list(F.struct("c", "z")))
        top = F.array_max(F.transform("zs", lambda p: p["z"]))
        shift = F.transform("zs", lambda p: F.exp(p["z"] - top))
        delta = F.transform("e", lambda x, c: x / F.aggregate("e", F.lit(0.0), lambda a, b: a + b) - (c == F.col("y")).cast("double"))
        one = score.groupBy("worker", "row_id", "y").agg(e.alias("zs")).withColumn("e", shift)
        error = one.select("worker", "row_id", F.posexplode(delta).alias("c", "d"))
    else:
        error = score.select("worker", "row_id", "c", (F.col("z") - F.col("y")).alias("d"))
    total = rows.select("worker", "row_id", "f", "v").join(error, ["worker", "row_id"])
    sums = total.groupBy("worker", (F.col("c") * width + F.col("f")).cast("int").alias("idx")).agg(F.sum(F.col("v") * F.col("d")).alias("g"))
    count = batch.groupBy("worker").agg(F.count(F.lit(1)).alias("n"))
    return sums.join(count, "worker").select("worker", "idx", (F.col("g") / F.col("n")).alias("g"))


def arrow_gradient(batch: DataFrame, params: dict[int, np.ndarray], model) -> DataFrame:
    """The same by numpy partial sums per batch: (worker, n, grad)."""

    def partial(batches):
        for b in batches:
            worker = np.asarray(b.column("worker"))
            x = np.asarray(b.column("x").flatten()).reshape(b.num_rows, -1)
            y = np.asarray(b.column("y"))
            ws, ns, gs = [], [], []
            for w in np.unique(worker):
                at = worker == w
                ws.append(int(w))
                ns.append(int(at.sum()))
                gs.append(model.grad_sum(params[int(w)], x[at], y[at]))
            yield pa.record_batch([pa.array(ws, pa.int32()), pa.array(ns, pa.int64()), pa.array(gs, pa.list_(pa.float64()))], ["worker", "n", "grad"])

    parts = batch.select("worker", "x", "y").mapInArrow(partial, "worker int, n long, grad array<double>")
    long = parts.select("worker", "n", F.posexplode("grad").alias("idx", "g"))
    return long.groupBy("worker", "idx").agg((F.sum("g") / F.sum("n")).alias("g"))


def half_step(
    params: DataFrame, grad: DataFrame, step: Column | float, takes_part: DataFrame | None = None, l2: float = 0.0
) -> DataFrame:
    """val - step * (g + l2 * val); a worker without a batch keeps its value but for the penalty.

    ``takes_part`` (worker, on_time): late workers' gradients are discarded.
    """
    out = params.join(grad, ["worker", "idx"], "left").withColumn("g", F.coalesce("g", F.lit(0.0)) + l2 * F.col("val"))
    if takes_part is not None:
        out = out.join(F.broadcast(takes_part.select("worker", "on_time")), "worker").withColumn(
            "g", F.when(F.col("on_time"), F.col("g")).otherwise(0.0)
        )
    step = step if isinstance(step, Column) else F.lit(float(step))
    return out.select("worker", "idx", (F.col("val") - step * F.col("g")).alias("val"))


def mix(half: DataFrame, weights: DataFrame) -> DataFrame:
    """Weighted sum of the half-steps each worker waited for, itself included."""
    joined = half.join(F.broadcast(weights.select("src", "dst", F.col("w").alias("_w"))), F.col("worker") == F.col("src"))
    return joined.groupBy(F.col("dst").alias("worker"), "idx").agg(F.sum(F.col("_w") * F.col("val")).alias("val"))


def combine_then_step(params: DataFrame, weights: DataFrame, grad: DataFrame, step: float) -> DataFrame:
    """Mix the old parameters, then subtract the gradient taken before mixing."""
    return half_step(mix(params, weights), grad, step)


def mean_model(params: DataFrame) -> DataFrame:
    return params.groupBy("idx").agg(F.avg("val").alias("val"))


def disagreement(params: DataFrame) -> DataFrame:
    """Largest and mean squared distance of a worker's parameters to their mean."""
    centre = mean_model(params).withColumnRenamed("val", "m")
    d = params.join(centre, "idx").groupBy("worker").agg(F.sum(F.pow(F.col("val") - F.col("m"), 2)).alias("d"))
    return d.agg(F.max("d").alias("largest"), F.avg("d").alias("mean"))
