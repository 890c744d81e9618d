"""Mixing sources to target weights by a low-discrepancy slot schedule.

Each source is a stream: its documents in a seeded shuffled order, cut into
blocks of equal token count.  Slots are numbered 0..N-1; slot k has the point
(k * g mod N) / N, a golden-ratio lattice, and belongs to the source whose
interval of cumulative slot shares holds the point.  The r-th slot of a source
takes the r-th block of its (repeating) stream, so every prefix of the schedule
is near the target weights and the whole of it meets them exactly.

Defined cases: a null text has no words; a null source is a source of its own,
last in order; rows without words take nothing; repeated rows take turns like
any others; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from consensus_spark.llm.durable import materialise
from consensus_spark.llm.prefix import hash_bucket, running_start
from consensus_spark.llm.rules import words_of

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MOST_REPEATS = 2
BLOCK_TOKENS = 128
SEED = 17


def sized(docs: DataFrame) -> DataFrame:
    """Id, source (as a non-null struct key) and number of words of every row."""
    return docs.select(
        "doc_id",
        F.struct(
            F.col("source").isNull().alias("missing"),
            F.coalesce(F.col("source").cast("string"), F.lit("")).alias("name"),
        ).alias("src"),
        F.size(words_of(F.col("text"))).cast("long").alias("size"),
    )


def source_targets(
    rows: DataFrame,
    weights: tuple[int, ...] = WEIGHTS,
    share: float = SHARE,
    most: int = MOST_REPEATS,
) -> DataFrame:
    """One row per source: size, weight, target.

    Targets are ``min(most * size, level * weight)`` for the one level at which they
    add up to the share: what remains after capped sources are set aside, sorted by
    the level at which each would reach its cap.
    """
    by = rows.groupBy("src").agg(F.sum("size").alias("source_size"))
    everything = W.orderBy(F.lit(1)).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    order = F.row_number().over(W.orderBy("src"))
    by = by.withColumn(
        "weight", F.element_at(cycle, (order - 1) % len(weights) + 1)
    ).withColumn("_cap", F.col("source_size").cast("double") * most)
    rising = W.orderBy(F.col("_cap") / F.col("weight"), "src").rowsBetween(
        W.unboundedPreceding, -1
    )
    before = lambda c: F.coalesce(F.sum(c).over(rising), F.lit(0.0))
    level = (F.sum("source_size").over(everything) * share - before("_cap")) / (
        F.sum("weight").over(everything) - before("weight")
    )
    by = by.withColumn("_level", level).withColumn(
        "_free", F.col("_cap") / F.col("weight") >= F.col("_level")
    )
    # passing a free source lowers the level, so the first free one has the highest
    final = F.max(F.when(F.col("_free"), F.col("_level"))).over(everything)
    return by.select(
        "src",
        "source_size",
        "weight",
        F.least(F.col("_cap"), F.coalesce(final, F.lit(0.0)) * F.col("weight")).alias("target"),
    )


def _golden_step(n: int) -> int:
    """The step nearest to n over the golden ratio that shares no factor with n."""
    near = max(1, round(n * (math.sqrt(5) - 1) / 2))
    for d in range(n + 1):
        for g in (near - d, near + d):
            if 0 < g and math.gcd(g, n) == 1:
                return g
    return 1


def _times_mod(x: Column, by: int, n: int) -> Column:
    if n < 1 << 31:
        return (x * F.lit(by).cast("long")) % F.lit(n).cast("long")
    wide = x.cast("decimal(19,0)") * F.lit(by).cast("decimal(19,0)")
    return (wide % F.lit(n).cast("decimal(19,0)")).cast("long")


def schedule(targets: DataFrame, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """The slots: ``slot``, ``src``, ``rank`` in the source, ``epoch``, ``block``, ``take``.

    The inverse of the lattice gives each source its slots directly, so no slot is
    compared with every source.
    """
    b = F.lit(block_tokens).cast("long")
    up = lambda a: F.floor((a + b - 1) / b).cast("long")
    size, goal = F.col("source_size"), F.col("_goal")
    plan = (
        targets.filter(size > 0)
        .withColumn("_goal", F.floor("target").cast("long"))
        .withColumn("_blocks", up(size))
        .withColumn("_epochs", F.floor(goal / size).cast("long"))
        .withColumn("_slots", F.col("_epochs") * F.col("_blocks") + up(goal - F.col("_epochs") * size))
        .withColumn(
            "_first",
            F.coalesce(
                F.sum("_slots").over(W.orderBy("src").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)
            ),
        )
    )
    n = plan.agg(F.sum("_slots")).first()[0] or 0
    back = pow(_golden_step(n), -1, n) if n > 1 else 0
    piece = 1 << 16
    points = (
        plan.filter(F.col("_slots") > 0)
        .withColumn("_piece", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("_slots") - 1) / piece))))
        .repartition("src", "_piece")
        .withColumn(
            "_x",
            F.explode(
                F.sequence(
                    F.col("_piece") * piece,
                    F.least(F.col("_slots"), (F.col("_piece") + 1) * piece) - 1,
                )
            ),
        )
        .withColumn("slot", _times_mod(F.col("_first") + F.col("_x"), back, max(n, 1)))
        .select("slot", "src", "source_size", "_goal", "_blocks")
    )
    width = max(1, -(-n // 1024))
    ranked = running_start(
        points, ["src"], F.floor(F.col("slot") / width), ["slot"], F.lit(1).cast("long"), "rank"
    )
    epoch = F.floor(F.col("rank") / F.col("_blocks")).cast("long")
    block = F.col("rank") % F.col("_blocks")
    length = F.least(b, F.col("source_size") - block * b)
    return ranked.select(
        "slot",
        "src",
        "rank",
        epoch.alias("epoch"),
        block.alias("block"),
        length.alias("block_size"),
        F.least(length, F.col("_goal") - (epoch * F.col("source_size") + block * b)).alias("take"),
    )


def mix(docs: DataFrame, block_tokens: int = BLOCK_TOKENS, seed: int = SEED) -> DataFrame:
    """Each row's id, source, size, source size, target and words taken."""
    rows = materialise(sized(docs))
    targets = materialise(source_targets(rows))
    slots = schedule(targets, block_tokens)
    # at most one slot of a block is cut short: the last of its source
    uses = slots.groupBy("src", "block").agg(
        F.sum((F.col("take") == F.col("block_size")).cast("long")).alias("_whole"),
        F.max(F.when(F.col("take") < F.col("block_size"), F.col("take")).otherwise(0)).alias("_part"),
    )
    streams = running_start(
        rows.filter(F.col("size") > 0).withColumn("_hash", F.xxhash64(F.lit(seed), "doc_id", "size")),
        ["src"],
        hash_bucket(F.col("_hash")),
        ["_hash", "doc_id"],
        F.col("size"),
        "_from",
    ).drop("_hash")
    b, start, end = F.lit(block_tokens).cast("long"), F.col("_from"), F.col("_from") + F.col("size")
    block = F.col("block")
    pieces = (
        streams.withColumn(
            "block", F.explode(F.sequence(F.floor(start / b), F.floor((end - 1) / b)))
        )
        .withColumn("_a", F.greatest(start - block * b, F.lit(0)))
        .withColumn("_b", F.least(end - block * b, b))
    )
    taken = F.coalesce(
        F.col("_whole") * (F.col("_b") - F.col("_a"))
        + F.greatest(F.lit(0), F.least(F.col("_b"), F.col("_part")) - F.col("_a")),
        F.lit(0),
    )
    used = (
        pieces.join(uses.hint("merge"), ["src", "block"], "left")
        .groupBy("src", "_from")
        .agg(F.first("doc_id").alias("doc_id"), F.first("size").alias("size"), F.sum(taken).alias("taken"))
        .select("src", "doc_id", "size", "taken")
    )
    bare = rows.filter(F.col("size") == 0).select(
        "src", "doc_id", "size", F.lit(0).cast("long").alias("taken")
    )
    return (
        used.unionByName(bare)
        .join(targets, "src")
        .select(
            "doc_id",
            F.when(~F.col("src.missing"), F.col("src.name")).alias("source"),
            "size",
            "source_size",
            "target",
            F.col("taken").cast("long").alias("taken"),
        )
    )


def op5_mixture(spark, sf_dir: str) -> DataFrame:
    """The mix of all documents."""
    return mix(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def apply_mix(docs: DataFrame, block_tokens: int = BLOCK_TOKENS, seed: int = SEED) -> DataFrame:
    """The mixed corpus: a row for each whole use of a document and one for a partial use.

    A partial use keeps the document's leading words; ``n_chars``, if there, follows.
    All columns of the input stay.  Rows that repeat id, source and size are matched
    to their shares one by one.
    """
    names = docs.columns
    clash = {c: f"_in_{i}" for i, c in enumerate(names)}
    held = docs.select(*[F.col(c).alias(x) for c, x in clash.items()])
    text = F.col(clash["text"])
    key = [F.col(clash["doc_id"]).alias("_id"), F.col(clash["source"]).cast("string").alias("_source")]
    held = held.select("*", *key, F.size(words_of(text)).cast("long").alias("_size"))
    same = W.partitionBy("_id", "_source", "_size")
    held = held.withColumn("_n", F.row_number().over(same.orderBy(text)))
    shares = mix(docs, block_tokens, seed).filter("taken > 0").select(
        F.col("doc_id").alias("_doc"), F.col("source").alias("_src"), F.col("size").alias("_len"), "taken"
    )
    shares = shares.withColumn(
        "_k", F.row_number().over(W.partitionBy("_doc", "_src", "_len").orderBy(F.desc("taken")))
    )
    on = (
        F.col("_id").eqNullSafe(F.col("_doc"))
        & F.col("_source").eqNullSafe(F.col("_src"))
        & (F.col("_size") == F.col("_len"))
        & (F.col("_n") == F.col("_k"))
    )
    whole, rest = F.floor(F.col("taken") / F.col("_size")).cast("int"), F.col("taken") % F.col("_size")
    uses = F.concat(
        F.array_repeat(F.lit(0).cast("long"), whole),
        F.when(rest > 0, F.array(rest)).otherwise(F.array().cast("array<bigint>")),
    )
    used = held.join(shares.hint("merge"), on).withColumn("_use", F.explode(uses))
    cut = F.array_join(F.slice(words_of(text), F.lit(1), F.col("_use").cast("int")), " ")
    columns = []
    for c, x in clash.items():
        value = F.col(x)
        if c == "text":
            value = F.when(F.col("_use") > 0, cut).otherwise(value)
        elif c == "n_chars":
            value = F.when(F.col("_use") > 0, F.length(cut).cast(docs.schema[c].dataType)).otherwise(value)
        columns.append(value.alias(c))
    return used.select(*columns)
