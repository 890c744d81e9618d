"""Bounded connectivity and positivity over windows of iterations."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from consensus_spark.sources.graphs import is_connected


def bounded_connectivity(active: DataFrame, n: int, last: int, window: int, mode: str = "aligned") -> DataFrame:
    """Whether the union of each window's active edges connects all workers.

    ``aligned`` takes blocks of ``window`` iterations, ``sliding`` every start.
    Reachability by repeated joins is avoided: a window's edges are at most n^2 and
    are searched inside the window's own group.
    """
    if mode == "aligned":
        placed = active.withColumn("window", F.floor((F.col("k") - 1) / window).cast("int"))
        first, count = 0, last // window
    else:
        placed = active.withColumn(
            "window", F.explode(F.sequence(F.greatest(F.lit(1), F.col("k") - window + 1), F.col("k")))
        )
        first, count = 1, last - window + 1
    unions = placed.groupBy("window").agg(F.collect_set(F.struct("src", "dst")).alias("edges"))
    spark = active.sparkSession
    all_windows = spark.range(first, first + max(count, 0)).select(F.col("id").cast("int").alias("window"))

    def judge(batches):
        for pdf in batches:
            ok = [e is not None and is_connected([(x["src"], x["dst"]) for x in e], n) or n == 1 for e in pdf["edges"]]
            yield pdf[["window"]].assign(connected=ok)

    return all_windows.join(unions, "window", "left").mapInPandas(judge, "window int, connected boolean")


def positivity(matrices: dict[int, np.ndarray], d: int, epochs: int) -> list[tuple[int, float, float]]:
    """(first epoch, least entry of the product over ``epochs`` epochs, its lower bound)."""
    beta = min(float(m[m > 0].min()) for m in matrices.values())
    whole, out = max(matrices) // d, []
    for e in range(whole - epochs + 1):
        p = np.eye(len(next(iter(matrices.values()))))
        for k in range(e * d + 1, (e + epochs) * d + 1):
            p = p @ matrices[k]
        out.append((e, float(p.min()), beta ** (epochs * d)))
    return out
