"""SimHash near-duplicates by multi-index hashing, and their linked groups.

Fingerprints are first made distinct, so copies cost one entry however many there
are.  Each 64-bit fingerprint is stored under its two 32-bit halves.  Two
fingerprints that differ in at most three bits differ in at most one bit in one of
the halves, so probing each half's ball of radius one (33 keys) finds every link;
complete distances are verified in the join.  Groups are found by alternating star
contractions, each round written to the shared folder.

Defined cases: a text without words has fingerprint zero and links like any other;
null text counts as empty; repeated rows and ties share one fingerprint entry;
a group whose ids are all null has a null component; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.types import AtomicType

from consensus_spark.llm.durable import materialise
from consensus_spark.llm.textbytes import flat_bytes

MAX_BITS = 3
SHINGLE = 3
SEED = 42

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32


def fingerprint(text: bytes, k: int = SHINGLE) -> int:
    """Majority bits of the XXH64 values of the k-word shingles of a lower-cased text."""
    words = text.split()
    if not words:
        return 0
    body, n = b" ".join(words), max(1, len(words) - k + 1)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    start = np.concatenate([[0], ends[:-1] + 1])[:n].tolist()
    stop = (ends[k - 1 :] if len(words) >= k else ends[-1:]).tolist()
    digest = xxhash.xxh64_intdigest
    ones = np.zeros(64, np.int64)
    for a in range(0, n, 1 << 16):
        part = [digest(body[s:e], SEED) for s, e in zip(start[a : a + (1 << 16)], stop[a : a + (1 << 16)], strict=True)]
        raw = np.array(part, ">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(raw, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > n).tobytes(), "big")


def _fingerprints(batches):
    for batch in batches:
        data, off = flat_bytes(batch.column("text"))
        low = _LOWER[data]
        prints = [fingerprint(low[a:z].tobytes()) for a, z in zip(off[:-1], off[1:], strict=True)]
        others = [c for c in batch.schema.names if c != "text"]
        yield pa.record_batch(
            [*(batch.column(c) for c in others), pa.array(np.array(prints, np.uint64).view(np.int64), pa.int64())],
            [*others, "print"],
        )


def fingerprints(docs: DataFrame) -> DataFrame:
    """``doc_id`` and ``print`` (the fingerprint's 64 bits as a long) of every row."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(
        _fingerprints, "doc_id long, print long"
    )


def links(prints: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """Pairs (a < b) of distinct fingerprints at ``max_bits`` or fewer differing bits."""
    if not 0 <= max_bits <= 3:
        raise ValueError("two halves with balls of radius one find up to 3 differing bits")
    half = lambda c: F.array(
        F.struct(F.lit(0).alias("part"), F.shiftrightunsigned(c, 32).alias("key")),
        F.struct(F.lit(1).alias("part"), c.bitwiseAND(F.lit(0xFFFFFFFF)).alias("key")),
    )
    flips = F.array(*[F.lit(v).cast("long") for v in [0, *[1 << i for i in range(32)]]])
    stored = prints.select(F.col("print").alias("b"), F.inline(half(F.col("print"))))
    probes = prints.select(F.col("print").alias("a"), F.inline(half(F.col("print")))).select(
        "a", "part", F.explode(F.transform(flips, lambda f: F.col("key").bitwiseXOR(f))).alias("key")
    )
    near = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= max_bits
    p, s = probes.alias("p"), stored.alias("s")
    on = (F.col("p.part") == F.col("s.part")) & (F.col("p.key") == F.col("s.key"))
    return p.join(s, on & (F.col("a") < F.col("b")) & near).select("a", "b").distinct()


def components(edges: DataFrame) -> DataFrame:
    """``node`` and ``root`` (the least node reachable) of every node on an edge.

    Alternates the large-star and small-star contractions until the edges stand
    still; each node's least neighbour comes from a partial aggregate, so a hub is
    never gathered in one task.
    """

    def least(pairs: DataFrame) -> DataFrame:
        return pairs.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))

    def large(e: DataFrame) -> DataFrame:
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        return (
            both.join(least(both), "u")
            .filter(F.col("v") > F.col("u"))
            .select(F.col("v").alias("u"), F.col("m").alias("v"))
            .filter("u <> v")
            .distinct()
        )

    def small(e: DataFrame) -> DataFrame:
        down = e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        low = least(down)
        moved = down.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        return moved.union(low.select("u", F.col("m").alias("v"))).filter("u <> v").distinct()

    def mark(e: DataFrame):
        return tuple(e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first())

    now = materialise(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    seen = None
    while (is_now := mark(now)) != seen:
        seen = is_now
        now = materialise(small(large(now)))
    ends = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return ends.union(now.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()


def _rooted(prints: DataFrame, least: Column, max_bits: int) -> DataFrame:
    """Each different fingerprint with the smallest ``least`` of its rows and its group's ``root``."""
    one = prints.groupBy("print").agg(F.min(least).alias("least"))
    roots = components(links(one.select("print"), max_bits))
    return one.join(roots, one["print"] == roots["node"], "left").select(
        "print", "least", F.coalesce("root", "print").alias("root")
    )


def groups(docs: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """``doc_id``, ``print``, ``component_id`` of every row."""
    prints = materialise(fingerprints(docs))
    labelled = _rooted(prints, F.col("doc_id"), max_bits)
    smallest = labelled.groupBy("root").agg(F.min("least").alias("component_id"))
    named = labelled.join(smallest, "root").select("print", "component_id")
    return prints.join(named, "print").select("doc_id", "print", "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """Exactly one row of each group of linked fingerprints, with all its columns.

    The smallest id stays, a null id after all others.  Of different texts with that
    id the one of least XXH64 stays, of rows equal in both the least by other columns.
    """
    names = docs.columns
    clash = [f"_in_{i}" for i in range(len(names))]
    as_doc = dict(zip(names, clash, strict=True))
    key = F.xxhash64("text").alias("key")
    prints = materialise(
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", key).mapInArrow(
            _fingerprints, "doc_id long, key long, print long"
        )
    )
    row = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "key")
    kept = (
        _rooted(prints, row, MAX_BITS)
        .groupBy("root")
        .agg(F.min("least").alias("least"))
        .select(F.col("least.doc_id").alias("_id"), F.col("least.key").alias("_key"))
    )
    held = docs.select(
        *[F.col(c).alias(x) for c, x in as_doc.items()],
        F.col("doc_id").cast("long").alias("_own"),
        key.alias("_text"),
    )
    out = held.join(kept, held["_own"].eqNullSafe(kept["_id"]) & (held["_text"] == kept["_key"]), "left_semi")
    order = [as_doc[f.name] for f in docs.schema if isinstance(f.dataType, AtomicType)]
    first = W.partitionBy("_own", "_text").orderBy(*order)
    out = out.withColumn("_n", F.row_number().over(first)).filter("_n = 1")
    return out.select(*[F.col(x).alias(c) for c, x in as_doc.items()])


def op10_simhash(spark, sf_dir: str) -> DataFrame:
    """Fingerprints and linked groups of all documents."""
    found = groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    digits = F.lower(F.lpad(F.hex("print"), 16, "0"))
    return found.select("doc_id", digits.alias("fingerprint"), "component_id")
