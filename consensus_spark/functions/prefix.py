"""Ranks inside groups of any size, without one task per group."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def rank_within(df: DataFrame, keys: list[str], bucket: Column, order: list[str], out: str) -> DataFrame:
    """Add ``out``: the place from 1 of each row among the rows of its keys.

    ``bucket`` must not fall as ``order`` rises.  Whole buckets are counted first, so
    only rows of one bucket meet in a task, however many rows the keys hold.
    """
    cut = df.withColumn("_bucket", bucket)
    part = [*keys, "_bucket"]
    upto = W.partitionBy(*keys).orderBy("_bucket").rowsBetween(W.unboundedPreceding, -1)
    starts = (
        cut.groupBy(*part)
        .agg(F.count(F.lit(1)).alias("_n"))
        .select(*part, F.coalesce(F.sum("_n").over(upto), F.lit(0)).alias("_start"))
    )
    local = cut.withColumn(out, F.row_number().over(W.partitionBy(*part).orderBy(*order)))
    return local.join(starts.hint("merge"), part).withColumn(out, F.col(out) + F.col("_start")).drop("_bucket", "_start")
