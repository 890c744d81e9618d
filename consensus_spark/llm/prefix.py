"""Running totals inside groups of any size, without one task per group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def running_start(
    df: DataFrame, keys: list[str], bucket: Column, order: list[str], value: Column, out: str
) -> DataFrame:
    """Add ``out``: the sum of ``value`` over the rows of the same keys that come before.

    ``bucket`` must not fall as ``order`` rises.  A group is cut into its buckets;
    the sums of whole buckets (one row each) give each bucket's start, and only
    inside a bucket are rows sorted.  A group that holds a third of all rows is
    therefore spread over as many tasks as it has buckets.  Keys must not be null.
    """
    cut = df.withColumn("_bucket", bucket).withColumn("_value", value)
    part = [*keys, "_bucket"]
    sums = cut.groupBy(*part).agg(F.sum("_value").alias("_sum"))
    upto = W.partitionBy(*keys).orderBy("_bucket").rowsBetween(W.unboundedPreceding, -1)
    starts = sums.select(*part, F.coalesce(F.sum("_sum").over(upto), F.lit(0)).alias("_start"))
    inside = W.partitionBy(*part).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    local = cut.withColumn("_local", F.coalesce(F.sum("_value").over(inside), F.lit(0)))
    return (
        local.join(starts.hint("merge"), part)  # explode hides sizes from the planner: never broadcast
        .withColumn(out, (F.col("_start") + F.col("_local")).cast("long"))
        .drop("_bucket", "_value", "_start", "_local")
    )


def hash_bucket(hashed: Column, bits: int = 10) -> Column:
    """The leading bits of a signed 64-bit hash: rises with the hash, even in size."""
    return F.shiftright(hashed, 64 - bits)
