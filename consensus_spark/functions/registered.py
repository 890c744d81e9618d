"""The engine's functions for SQL text: SQL-defined, pandas and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

_SQL = {
    "vector_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vector_axpy(alpha DOUBLE, x ARRAY<DOUBLE>, y ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "zip_with(x, y, (u, v) -> alpha * u + v)",
    "metropolis_weight(a BIGINT, b BIGINT) RETURNS DOUBLE": "1D / (1 + greatest(a, b))",
    "geometric_step(k INT) RETURNS DOUBLE": "0.2D * power(0.95D, k)",
}


@F.pandas_udf(DoubleType())
def excess(t: pd.Series, cutoff: pd.Series) -> pd.Series:
    """Time past the cutoff, zero if on time."""
    return (t - cutoff).clip(lower=0)


@F.pandas_udf(DoubleType())
def spread(v: pd.Series) -> float:
    """Largest less smallest of a group: groups are iterations, of one value a worker."""
    return float(v.max() - v.min())


class CoverLinks:
    """Links of a cover of a named topology, in order: ``lid``, ``a``, ``b``."""

    def eval(self, topology: str, n: int):
        from consensus_spark.operators.cover import find_cover
        from consensus_spark.sources.graphs import graph

        for i, (a, b) in enumerate(find_cover(graph(topology, n, 5), n)):
            yield i, a, b


def register(spark: SparkSession) -> None:
    """Make all of them known to the session's SQL."""
    for head, body in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udf.register("excess", excess)
    spark.udf.register("spread", spread)
    spark.udtf.register("cover_links", F.udtf(CoverLinks, returnType="lid int, a int, b int"))
