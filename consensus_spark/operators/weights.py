"""Mixing weights on the active graph, and checks of them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def _square(active: DataFrame, workers: DataFrame, off: DataFrame) -> DataFrame:
    """Off-diagonal weights plus the diagonal remainder of every (k, worker)."""
    rest = off.groupBy("k", F.col("dst").alias("worker")).agg(F.sum("w").alias("s"))
    diagonal = workers.join(rest, ["k", "worker"], "left").select(
        "k", F.col("worker").alias("src"), F.col("worker").alias("dst"),
        (F.lit(1.0) - F.coalesce("s", F.lit(0.0))).alias("w"),
    )
    return off.select("k", "src", "dst", "w").unionByName(diagonal)


def metropolis(active: DataFrame, workers: DataFrame) -> DataFrame:
    """1 / (1 + larger active degree) on active edges, the remainder on the diagonal.

    Degrees come from windows over the edges themselves: no self-join.
    """
    out_degree = F.count(F.lit(1)).over(W.partitionBy("k", "src"))
    in_degree = F.count(F.lit(1)).over(W.partitionBy("k", "dst"))
    off = active.withColumn("_a", out_degree).withColumn("_b", in_degree).select(
        "k", "src", "dst", (F.lit(1.0) / (F.lit(1) + F.greatest("_a", "_b"))).alias("w")
    )
    return _square(active, workers.select("k", "worker"), off)


def receiver_mean(active: DataFrame, workers: DataFrame) -> DataFrame:
    """Each receiver averages itself and those it waited for; rows need not sum to one."""
    off = active.withColumn("w", F.lit(1.0) / (1 + F.count(F.lit(1)).over(W.partitionBy("k", "dst"))))
    return _square(active, workers.select("k", "worker"), off)


def max_degree(active: DataFrame, workers: DataFrame) -> DataFrame:
    """1 / (1 + largest degree of the iteration)."""
    degrees = active.groupBy("k", "dst").agg(F.count(F.lit(1)).alias("d")).groupBy("k").agg(F.max("d").alias("d"))
    off = active.join(degrees, "k").select("k", "src", "dst", (F.lit(1.0) / (1 + F.col("d"))).alias("w"))
    return _square(active, workers.select("k", "worker"), off)


def uniform(workers: DataFrame, n: int) -> DataFrame:
    """1/N everywhere: exact averaging."""
    w = workers.select("k", F.col("worker").alias("dst"))
    return w.withColumn("src", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).select(
        "k", "src", "dst", F.lit(1.0 / n).alias("w")
    )


def stochasticity(mix: DataFrame) -> DataFrame:
    """Per iteration: largest deviation of column and row sums from one, least entry."""
    side = lambda c: mix.groupBy("k", c).agg(F.sum("w").alias("s"), F.min("w").alias("m")).groupBy("k").agg(
        F.max(F.abs(F.col("s") - 1)).alias(f"{c}_deviation"), F.min("m").alias(f"{c}_least")
    )
    return side("dst").join(side("src"), "k").select("k", "dst_deviation", "src_deviation", F.col("dst_least").alias("least"))


def smallest_weight(mix: DataFrame) -> DataFrame:
    return mix.agg(F.min(F.when(F.col("w") > 0, F.col("w"))).alias("beta"))


def mix_product(mix: DataFrame, first: int, last: int) -> DataFrame:
    """Ordered product of the mixing matrices of iterations first..last: (src, dst, w)."""
    out = mix.filter(F.col("k") == first).select("src", "dst", "w")
    for k in range(first + 1, last + 1):
        nxt = mix.filter(F.col("k") == k).select(F.col("src").alias("mid"), F.col("dst").alias("to"), F.col("w").alias("v"))
        out = (
            out.join(nxt, F.col("dst") == F.col("mid"))
            .groupBy("src", "to")
            .agg(F.sum(F.col("w") * F.col("v")).alias("w"))
            .select("src", F.col("to").alias("dst"), "w")
        )
    return out


def matrices(mix: DataFrame, n: int, most: int = 64 << 20) -> dict[int, np.ndarray]:
    """Dense matrices on the driver; their number times n^2 is checked first."""
    ks = mix.select("k").distinct().count()
    if ks * n * n * 8 > most:
        raise ValueError("too many matrices for the driver; use mix_product")
    out: dict[int, np.ndarray] = {}
    for r in mix.collect():
        out.setdefault(r["k"], np.zeros((n, n)))[r["src"], r["dst"]] = r["w"]
    return out


def in_order(mix: DataFrame, n: int):
    """(k, dense matrix) of every iteration, rising; the driver holds one partition at a time."""
    cells = mix.groupBy("k").agg(F.collect_list(F.struct("src", "dst", "w")).alias("cells")).orderBy("k")
    for r in cells.toLocalIterator():
        m = np.zeros((n, n))
        for src, dst, w in r["cells"]:
            m[src, dst] = w
        yield r["k"], m


def weights_of(kind: str, active: DataFrame, workers: DataFrame, n: int) -> DataFrame:
    if kind == "uniform":
        return uniform(workers, n)
    return {"metropolis": metropolis, "receiver_mean": receiver_mean, "max_degree": max_degree}[kind](active, workers)


def rounded(c: Column | str, digits: int = 6) -> Column:
    """Rounded, without negative zero."""
    return F.round(F.col(c) if isinstance(c, str) else c, digits) + F.lit(0.0)
