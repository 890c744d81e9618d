"""Durations, clocks, backups and messages of a plan.

Time is a modelled clock computed from compute times; it says nothing about how long
Spark's own stages take.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def worker_wait(active: DataFrame, times: DataFrame) -> DataFrame:
    """Per worker and iteration: the largest time waited for; null with an empty wait set."""
    waited = active.join(times.select("k", F.col("worker").alias("src"), "t"), ["k", "src"])
    own = waited.groupBy("k", F.col("dst").alias("worker")).agg(F.max("t").alias("wait"))
    return times.select("k", "worker").join(own, ["k", "worker"], "left")


def iteration_duration(active: DataFrame, times: DataFrame) -> DataFrame:
    """The slowest compute time among workers actually waited for; 0 if nobody is."""
    asked = active.select("k", F.col("src").alias("worker")).distinct()
    slow = times.join(asked, ["k", "worker"]).groupBy("k").agg(F.max("t").alias("duration"))
    return times.select("k").distinct().join(slow, "k", "left").select("k", F.coalesce("duration", F.lit(0.0)).alias("duration"))


def clock(durations: DataFrame, chunk: int = 4096) -> DataFrame:
    """Running total of durations: chunk totals first, then inside chunks."""
    cut = durations.withColumn("_c", F.floor(F.col("k") / chunk))
    sums = cut.groupBy("_c").agg(F.sum("duration").alias("_s"))
    upto = W.orderBy("_c").rowsBetween(W.unboundedPreceding, -1)
    starts = sums.select("_c", F.coalesce(F.sum("_s").over(upto), F.lit(0.0)).alias("_start"))
    inside = W.partitionBy("_c").orderBy("k").rowsBetween(W.unboundedPreceding, 0)
    return (
        cut.withColumn("_l", F.sum("duration").over(inside))
        .join(F.broadcast(starts), "_c")
        .select("k", "duration", (F.col("_start") + F.col("_l")).alias("clock"))
    )


def duration_estimate(durations: DataFrame) -> DataFrame:
    """The best constant guess of a duration is its mean; its error is the variance."""
    return durations.agg(F.avg("duration").alias("estimate"), F.var_pop("duration").alias("mse"))


def duration_mse(durations: DataFrame, guess: float) -> DataFrame:
    return durations.agg(F.avg(F.pow(F.col("duration") - guess, 2)).alias("mse"))


def duration_reduction(base: DataFrame, other: DataFrame) -> DataFrame:
    """1 - mean(other)/mean(base), and mean and median of the per-iteration ratio."""
    both = base.select("k", F.col("duration").alias("full")).join(other.select("k", F.col("duration").alias("own")), "k")
    ratio = F.col("own") / F.col("full")
    return both.agg(
        (1 - F.avg("own") / F.avg("full")).alias("reduction"),
        F.avg(1 - ratio).alias("mean_ratio_reduction"),
        F.percentile(1 - ratio, F.lit(0.5)).alias("median_ratio_reduction"),
    )


def dominance(base: DataFrame, other: DataFrame) -> DataFrame:
    """Whether the base is never shorter, iteration by iteration."""
    both = base.select("k", F.col("duration").alias("full")).join(other.select("k", F.col("duration").alias("own")), "k")
    return both.agg(
        F.bool_and(F.col("full") >= F.col("own")).alias("holds"),
        F.count(F.lit(1)).alias("iterations"),
        F.sum((F.col("full") > F.col("own")).cast("long")).alias("strictly"),
    )


def backup_mean(wait: DataFrame) -> DataFrame:
    """Per iteration the mean number of backups of a worker."""
    return wait.groupBy("k").agg(F.avg("n_backup").alias("mean_backup"))


def participation(schedule: DataFrame, times: DataFrame) -> DataFrame:
    """Share of iterations in which each worker is on time."""
    t = times.join(schedule.select("k", "cutoff"), "k")
    return t.groupBy("worker").agg(F.avg((F.col("t") <= F.col("cutoff")).cast("double")).alias("share"))


def messages(active: DataFrame, n_parameters: int) -> DataFrame:
    """Per iteration: parameter messages, their bytes, and messages at the busiest worker."""
    per = active.groupBy("k", "dst").agg(F.count(F.lit(1)).alias("m"))
    return per.groupBy("k").agg(
        F.sum("m").alias("messages"), (F.sum("m") * 8 * n_parameters).alias("bytes"), F.max("m").alias("busiest")
    )


def control_overhead(n: Column, d: Column) -> Column:
    """Control messages of an epoch: in each of d iterations two ends tell all n workers."""
    return 2 * n * d


def moving_average(durations: DataFrame, width: int = 10) -> DataFrame:
    """Mean over the last ``width`` iterations; frames cross chunks by overlap."""
    span = 1000 * width
    shared = durations.withColumn(
        "_c", F.explode(F.array_distinct(F.array(F.floor(F.col("k") / span), F.floor((F.col("k") + width - 1) / span))))
    )
    frame = W.partitionBy("_c").orderBy("k").rowsBetween(1 - width, 0)
    smooth = shared.withColumn("smooth", F.avg("duration").over(frame))
    return smooth.filter(F.col("_c") == F.floor(F.col("k") / span)).select("k", "smooth")
