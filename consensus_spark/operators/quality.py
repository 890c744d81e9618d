"""Accuracy measures of parameters on examples."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from consensus_spark.functions.vectors import argmax, logits
from consensus_spark.operators.mixing import mean_model, packed


def _with_mean(ex: DataFrame, params: DataFrame) -> DataFrame:
    flat = F.array_sort(F.collect_list(F.struct("idx", "val")))
    one = mean_model(params).agg(F.transform(flat, lambda p: p["val"]).alias("w"))  # one row
    return ex.join(F.broadcast(one), F.lit(True))


def worker_mean_loss(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    """Mean over workers of each worker's mean loss at the mean model."""
    rows = _with_mean(ex, params).select("worker", model.loss_column(F.col("w"), F.col("x"), F.col("y")).alias("l"))
    return rows.groupBy("worker").agg(F.avg("l").alias("l")).agg(F.avg("l").alias("loss"))


def pooled_loss(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    rows = _with_mean(ex, params).select(model.loss_column(F.col("w"), F.col("x"), F.col("y")).alias("l"))
    return rows.agg(F.avg("l").alias("loss"), F.sum("l").alias("total"))


def predictions(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    z = logits(F.col("w"), F.col("x"), model.n_features, model.n_classes)
    return _with_mean(ex, params).select("row_id", "y", argmax(z).alias("predicted"))


def test_error(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    p = predictions(ex, params, model)
    return p.agg(F.avg((F.col("y") != F.col("predicted")).cast("double")).alias("error"), F.count(F.lit(1)).alias("n"))


def worker_losses(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    """Mean loss over all rows of each worker's own model: (owner, loss)."""
    own = packed(params).select(F.col("worker").alias("owner"), "w")  # one row per worker
    rows = ex.drop("worker").join(F.broadcast(own), F.lit(True))
    return rows.select("owner", model.loss_column(F.col("w"), F.col("x"), F.col("y")).alias("l")).groupBy("owner").agg(F.avg("l").alias("loss"))


def worker_errors(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    """Error of each worker's own model over all rows: (worker, error)."""
    rows = ex.drop("worker").join(F.broadcast(packed(params)), F.lit(True))
    wrong = argmax(logits(F.col("w"), F.col("x"), model.n_features, model.n_classes)) != F.col("y")
    return rows.select("worker", wrong.cast("double").alias("e")).groupBy("worker").agg(F.avg("e").alias("error"))


def confusion(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    return predictions(ex, params, model).groupBy("y", "predicted").agg(F.count(F.lit(1)).alias("n"))


def gradient_norm(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    """Squared norm of each worker's full gradient at its own parameters."""
    from consensus_spark.operators.mixing import local_gradient

    return local_gradient(ex, params, model).groupBy("worker").agg(F.sum(F.col("g") * F.col("g")).alias("norm2"))


def gradient_variance(ex: DataFrame, params: DataFrame, model) -> DataFrame:
    """Per worker: mean squared distance of a row's gradient to the worker's mean gradient."""
    own = ex.join(F.broadcast(packed(params)), "worker")
    rows = own.select("worker", "row_id", F.posexplode(model.grad_column(F.col("w"), F.col("x"), F.col("y"))).alias("idx", "g"))
    return rows.groupBy("worker", "idx").agg(F.var_pop("g").alias("v")).groupBy("worker").agg(F.sum("v").alias("variance"))


def iterations_to(history: DataFrame, column: str, target: float) -> DataFrame:
    """First iteration and clock at which the column is at or below the target; null if never."""
    hit = F.col(column) <= target
    return history.groupBy("run").agg(F.min(F.when(hit, F.col("k"))).alias("k"), F.min(F.when(hit, F.col("clock"))).alias("clock"))


def gram(ex: DataFrame) -> DataFrame:
    """Second-moment matrix and feature-target products: partial sums, no wide rows."""
    pairs = ex.select("y", "x", F.posexplode("x").alias("i", "a")).select("y", "i", "a", F.posexplode("x").alias("j", "b"))
    return pairs.groupBy("i", "j").agg(F.avg(F.col("a") * F.col("b")).alias("xx"))


def moment(ex: DataFrame) -> DataFrame:
    return ex.select("y", F.posexplode("x").alias("i", "a")).groupBy("i").agg(F.avg(F.col("a") * F.col("y")).alias("xy"))
