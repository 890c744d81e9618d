"""Compute times: a trace of events, or laws by inverse distribution of md5 uniforms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from consensus_spark.functions.hashing import uniform
from consensus_spark.functions.prefix import rank_within


def trace_from_events(events: DataFrame, n: int) -> DataFrame:
    """The k-th event of bucket ``user_id % n`` gives worker, time ``value``; k while all have one."""
    e = events.select(
        (F.col("user_id") % n).cast("int").alias("worker"), F.col("value").alias("t"), "ts", "event_id"
    ).filter("t IS NOT NULL")
    ranked = rank_within(e, ["worker"], F.date_trunc("day", "ts"), ["ts", "event_id"], "k")
    shortest = ranked.groupBy("worker").agg(F.max("k").alias("m")).agg(F.min("m").alias("last"), F.count(F.lit(1)).alias("w"))
    # one row: the last k of the worker with the fewest events
    return (
        ranked.join(F.broadcast(shortest), F.col("k") <= F.col("last"))
        .filter(F.col("w") == n)
        .select(F.col("k").cast("int").alias("k"), "worker", "t")
    )


def _law(name: str, u: Column, worker: Column, p: dict) -> Column:
    if name == "exponential":
        return -F.log(1 - u) * p.get("mean", 1.0)
    if name == "shifted_exponential":
        return p.get("shift", 1.0) - F.log(1 - u) * p.get("mean", 1.0)
    if name == "pareto":
        return p.get("shift", 1.0) + F.pow(1 - u, F.lit(-1 / p.get("shape", 1.5)))
    if name == "uniform":
        return p.get("low", 0.5) + u * (p.get("high", 1.5) - p.get("low", 0.5))
    if name == "slow_one":
        return (0.5 + u) * F.when(worker == p.get("worker", 0), p.get("factor", 5.0)).otherwise(1.0)
    if name == "size_proportional":
        sizes = F.array(*[F.lit(float(s)) for s in p["sizes"]])
        return F.element_at(sizes, worker + 1) * (1 + p.get("noise", 0.1) * (u - 0.5))
    raise ValueError(f"no law {name}")


def law(spark: SparkSession, name: str, n: int, last: int, seed: int = 0, **p) -> DataFrame:
    """Times of ``n`` workers over iterations 1..last."""
    rows = spark.range(last * n).select(
        (F.floor(F.col("id") / n) + 1).cast("int").alias("k"), (F.col("id") % n).cast("int").alias("worker")
    )
    u = uniform(seed, "worker", "k")
    if name == "random_slow":
        slow = uniform(f"{seed}s", "worker", "k") < p.get("chance", 0.1)
        return rows.withColumn("t", (0.5 + u) * F.when(slow, p.get("factor", 10.0)).otherwise(1.0))
    if name == "one_random_slow":
        chosen = F.floor(uniform(f"{seed}c", "k") * n).cast("int")
        return rows.withColumn("t", (0.5 + u) * F.when(F.col("worker") == chosen, p.get("factor", 10.0)).otherwise(1.0))
    return rows.withColumn("t", _law(name, u, F.col("worker"), p))


def measured(log: DataFrame) -> DataFrame:
    """Times from a run log of (k, worker, seconds): the sum over a worker's tasks."""
    return log.groupBy("k", "worker").agg(F.sum("seconds").alias("t"))
