"""Lineage cuts that survive lost executors."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a local one only in local mode without it."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    path = os.path.join(tempfile.gettempdir(), "checkpoints")
    os.makedirs(path, exist_ok=True)
    return f"file://{path}"


def materialise(df: DataFrame) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back.

    The result has no lineage behind it: a lost executor costs a re-read, not a
    re-computation, and every later use sees the same rows.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/corpus-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bucketed(df: DataFrame, key: str, n: int) -> DataFrame:
    """``materialise`` with the rows of a key in one of ``n`` buckets: a join by key moves only the other side.

    The catalog names the table only until it is read; its files stay in the shared folder.
    """
    spark = df.sparkSession
    name = f"corpus_{uuid.uuid4().hex}"
    df.write.format("parquet").bucketBy(n, key).option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    made = spark.table(name)
    made.schema  # analysed before its name goes
    spark.sql(f"DROP TABLE {name}")
    return made
