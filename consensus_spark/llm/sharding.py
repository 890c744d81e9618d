"""Jump consistent hashing of stable keys to shards, with gapless slots.

Native: the whole path is DataFrame expressions.

Defined cases: a null text has size 1 and the CRC of the empty string; a null
key hashes as its own key (shard of key 0's complement); repeated rows of one
key share a shard and take slots of their own; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from consensus_spark.llm.prefix import hash_bucket, running_start

# Fixed values of the published generator: multiplier and increment modulo 2^64.
MULTIPLIER = 2862933555777941757
INCREMENT = 1

_LOW32 = (1 << 32) - 1
_A_HIGH, _A_LOW = MULTIPLIER >> 32, MULTIPLIER & _LOW32
_A_LOW_HIGH, _A_LOW_LOW = _A_LOW >> 16, _A_LOW & 0xFFFF


def _advance(high: Column, low: Column) -> tuple[Column, Column]:
    """One step of the generator on a state held as two 32-bit halves.

    Every intermediate value stays below 2^63, so the expression is the same
    with and without ANSI overflow checks.
    """
    by_high = low * F.lit(_A_LOW_HIGH)
    total = (
        low * F.lit(_A_LOW_LOW)
        + F.shiftleft(by_high.bitwiseAND(F.lit(0xFFFF)), 16)
        + F.lit(INCREMENT)
    )
    carry = F.shiftright(total, 32) + F.shiftright(by_high, 16)
    upper = (
        carry
        + low * F.lit(_A_HIGH)
        + high * F.lit(_A_LOW_LOW)
        + F.shiftleft((high * F.lit(_A_LOW_HIGH)).bitwiseAND(F.lit(0xFFFF)), 16)
    )
    return upper.bitwiseAND(F.lit(_LOW32)), total.bitwiseAND(F.lit(_LOW32))


def jump_shard(key: Column, n_shards: int) -> Column:
    """Shard of ``key`` among ``n_shards``: each jump moves to a higher bucket or ends.

    Bucket numbers rise strictly, so ``n_shards`` steps always suffice.
    """
    if n_shards < 1:
        raise ValueError("n_shards must be at least 1")
    key = F.coalesce(key.cast("long"), F.lit(-1).cast("long"))
    start = F.struct(
        F.shiftrightunsigned(key, 32).alias("high"),
        key.bitwiseAND(F.lit(_LOW32)).alias("low"),
        F.lit(-1).cast("long").alias("b"),
        F.lit(0).cast("long").alias("j"),
    )

    def step(state: Column, _: Column) -> Column:
        high, low = _advance(state["high"], state["low"])
        # the divisor is the state's leading 31 bits plus one
        reach = (state["j"] + 1).cast("double") * (
            F.lit(float(1 << 31)) / (F.shiftright(high, 1) + 1).cast("double")
        )
        moved = F.struct(
            high.alias("high"),
            low.alias("low"),
            state["j"].alias("b"),
            F.floor(F.least(reach, F.lit(float(1 << 52)))).cast("long").alias("j"),
        )
        return F.when(state["j"] < n_shards, moved).otherwise(state)

    steps = F.sequence(F.lit(1), F.lit(n_shards))
    return F.aggregate(steps, start, step, lambda state: state["b"].cast("int"))


def shard_documents(
    docs: DataFrame, n_shards: int = 16, key: str = "doc_id", text: str = "text"
) -> DataFrame:
    """Place each row: shard by key, slot inside the shard, and its shard among one more.

    Only the key decides, so appending a shard moves rows into that shard alone.
    """
    keyed = docs.select(
        F.col(key).alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col(text), F.lit("")).cast("binary")).alias("text_crc32"),
        jump_shard(F.col(key), n_shards).alias("shard"),
        jump_shard(F.col(key), n_shards + 1).alias("grown_shard"),
    ).withColumn("_spread", F.xxhash64(F.coalesce("doc_id", F.lit(-1))))
    placed = running_start(
        keyed,
        ["shard"],
        hash_bucket(F.col("_spread")),
        ["_spread", "doc_id", "size", "text_crc32"],
        F.lit(1).cast("long"),
        "slot",
    )
    return placed.select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard"
    )


def op2_shards(spark, sf_dir: str) -> DataFrame:
    """Shards 0 to 15 of all documents."""
    return shard_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
