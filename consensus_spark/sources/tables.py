"""Given tables, slot-partitioned examples and run histories on Parquet."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TIMES = T.StructType(
    [T.StructField("k", T.IntegerType()), T.StructField("worker", T.IntegerType()), T.StructField("t", T.DoubleType())]
)
EDGE = T.StructType([T.StructField("src", T.IntegerType()), T.StructField("dst", T.IntegerType())])
LINK = T.StructType(
    [T.StructField("lid", T.IntegerType()), T.StructField("a", T.IntegerType()), T.StructField("b", T.IntegerType())]
)
EVENTS = T.StructType(
    [
        T.StructField("event_id", T.LongType()),
        T.StructField("ts", T.TimestampNTZType()),
        T.StructField("user_id", T.LongType()),
        T.StructField("event_type", T.StringType()),
        T.StructField("value", T.DoubleType()),
        T.StructField("props", T.StringType()),
    ]
)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def save_slots(examples: DataFrame, path: str) -> None:
    """Examples laid out so that one iteration reads one directory."""
    examples.repartition("slot", "worker").write.mode("overwrite").partitionBy("slot").parquet(path)


def read_slot(spark: SparkSession, path: str, slot: int) -> DataFrame:
    """A partition-pruned read of one slot."""
    return spark.read.parquet(path).filter(F.col("slot") == slot)


def append_history(history: DataFrame, path: str) -> None:
    history.write.mode("append").partitionBy("run").parquet(path)


def read_rows(spark: SparkSession, path: str, kind: str, schema: T.StructType) -> DataFrame:
    """CSV, JSON, ORC or Parquet under an explicit schema (no inference pass)."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.format(kind).load(path)


def write_rows(df: DataFrame, path: str, kind: str) -> None:
    writer = df.write.mode("overwrite")
    writer.option("header", True).csv(path) if kind == "csv" else writer.format(kind).save(path)
