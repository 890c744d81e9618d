"""Training tasks on the given tables, shards and mini-batches."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from consensus_spark.functions.hashing import bucket, word
from consensus_spark.functions.prefix import rank_within
from consensus_spark.functions.vectors import argmax, dot, let
from consensus_spark.sources.tables import load

# Letters of the language task.
LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßéèçñóíê"
SMALL_LETTERS = "aehinu"
LANGUAGES = ("de", "en", "es", "fr")
CENTRE, SCALE = 0.04, 25.0
TIER_CUTS = (33_800.0, 66_800.0)
SEED = 1


def letter_shares(text: Column, letters: str) -> Column:
    """Share of each letter, centred and scaled by fixed numbers, and a constant."""
    low = F.lower(text)
    n = F.length(low).cast("double")
    part = lambda c: (n - F.length(F.replace(low, F.lit(c), F.lit("")))) / n
    return F.array(*[(part(c) - CENTRE) * SCALE for c in letters], F.lit(1.0))


def language_examples(docs: DataFrame, letters: str = LETTERS) -> DataFrame:
    """``row_id``, ``x``, ``y`` (rank of the language), ``is_test`` (one in seven)."""
    rank = F.array_position(F.array(*[F.lit(v) for v in LANGUAGES]), F.col("lang")) - 1
    return docs.filter("length(text) > 0").select(
        F.col("doc_id").alias("row_id"),
        letter_shares(F.col("text"), letters).alias("x"),
        rank.cast("int").alias("y"),
        (word("test", "doc_id") % 7 == 0).alias("is_test"),
    )


def planted_weight(cls: int, idx: int) -> str:
    return f"{cls}|{idx}"


def planted_examples(emb: DataFrame, n_classes: int = 10, seed: int = SEED, noise: bool = False) -> DataFrame:
    """Unit vectors; label by the largest of fixed linear maps (or the table's own label)."""
    def u(c: int, i: int) -> float:
        return int(hashlib.md5(f"{seed}|{c}|{i}".encode()).hexdigest()[:8], 16) / (1 << 32) - 0.5

    x = F.transform("embedding", lambda v: v.cast("double"))
    maps = F.array(*[F.array(*[F.lit(u(c, i)) for i in range(64)]) for c in range(n_classes)])
    y = F.col("label").cast("int") if noise else argmax(F.transform(maps, lambda w: dot(w, F.col("e"))))
    return emb.filter("embedding IS NOT NULL").select("vec_id", "label", x.alias("e")).select(
        F.col("vec_id").alias("row_id"),
        F.array_append(F.transform("e", lambda v: v * 8.0), F.lit(1.0)).alias("x"),
        y.alias("y"),
        (word("test", "vec_id") % 6 == 0).alias("is_test"),
    )


def revenue_examples(items: DataFrame, target: str = "tier") -> DataFrame:
    """Four scaled line-item numbers and a constant; revenue tier or scaled revenue."""
    money = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    y = (
        F.when(money < TIER_CUTS[0], 0).when(money < TIER_CUTS[1], 1).otherwise(2).cast("int")
        if target == "tier"
        else (money - 50_000.0) / 30_000.0
    )
    key = F.concat_ws("-", "l_orderkey", "l_linenumber")
    return items.select(
        (F.col("l_orderkey") * 10 + F.col("l_linenumber")).alias("row_id"),
        F.array(
            (F.col("l_quantity") - 25.5) / 14.4, (F.col("l_extendedprice") - 52_500.0) / 30_000.0,
            (F.col("l_discount") - 0.05) / 0.03, (F.col("l_tax") - 0.04) / 0.025, F.lit(1.0),
        ).alias("x"),
        y.alias("y"),
        (word("test", key) % 7 == 0).alias("is_test"),
    )


def bigram_hash(text: Column, dims: int) -> Column:
    """Shares of hashed letter pairs, by md5 of the pair."""
    low = F.lower(text)
    n = F.greatest(F.length(low) - 1, F.lit(1))
    pairs = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(low, i, F.lit(2)))
    slot = F.transform(pairs, lambda p: (F.conv(F.substring(F.md5(p), 1, 8), 16, 10).cast("long") % dims).cast("int"))
    return F.transform(
        F.sequence(F.lit(0), F.lit(dims - 1)), lambda d: F.size(F.filter(slot, lambda s: s == d)) / n.cast("double")
    )


QUALITY_SIGNS = LETTERS + "#$%&*|!"


def quality_examples(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Labelled documents by shares of letters and signs over their whole text."""
    held = docs.join(labels.select("doc_id", "quality"), "doc_id")
    return held.filter("length(text) > 0").select(
        F.col("doc_id").alias("row_id"), letter_shares(F.col("text"), QUALITY_SIGNS).alias("x"),
        F.col("quality").cast("int").alias("y"), (word("test", "doc_id") % 7 == 0).alias("is_test"),
    )


def clean_examples(ex: DataFrame, on_null: str = "reject") -> DataFrame:
    """Reject or zero-fill null and non-finite features."""
    bad = lambda v: v.isNull() | F.isnan(v)
    if on_null == "reject":
        return ex.filter(F.col("x").isNotNull() & ~F.exists("x", bad) & F.col("y").isNotNull())
    return ex.withColumn("x", F.transform("x", lambda v: F.when(bad(v), 0.0).otherwise(v)))


def standardise(ex: DataFrame, how: str = "global") -> DataFrame:
    """Centre each feature; divide by its own deviation or by one global number.

    Features whose values never change keep their value.
    """
    long = ex.select("row_id", F.posexplode("x").alias("i", "v"))
    per = long.groupBy("i").agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("s"))
    packed = per.agg(F.array_sort(F.collect_list(F.struct("i", "m", "s"))).alias("stat"))  # one row
    size = F.sqrt(F.aggregate("stat", F.lit(0.0), lambda a, z: a + z["s"] * z["s"]) / F.size("stat"))
    out = ex.join(F.broadcast(packed), F.lit(True)).withColumn("_g", size)
    scale = (lambda z: F.col("_g")) if how == "global" else (lambda z: z["s"])
    x = F.zip_with("x", "stat", lambda v, z: F.when(z["s"] > 0, (v - z["m"]) / scale(z)).otherwise(v))
    return out.withColumn("x", x).drop("stat", "_g")


def dirichlet_cuts(alpha: float, n: int, classes: int, seed: int) -> np.ndarray:
    """Upper edges of the workers' quotas in [0, 1) for each label."""
    return np.cumsum(np.random.default_rng(seed).dirichlet([alpha] * n, classes), axis=1)


def bigram_examples(docs: DataFrame, dims: int) -> DataFrame:
    """``row_id``, ``x``: the shares of ``bigram_hash``, with one md5 per different pair of a batch."""

    def shares(batches):
        for b in batches:
            place: dict[str, int] = {}
            out = []
            for t in b.column("low").to_pylist():
                code = np.frombuffer(t.encode("utf-32-le"), "<u4").astype(np.uint64)
                pair, count = np.unique((code[:-1] << np.uint64(32)) | code[1:], return_counts=True)
                x = np.zeros(dims)
                for p, c in zip(pair.tolist(), count.tolist(), strict=True):
                    key = chr(p >> 32) + chr(p & 0xFFFFFFFF)
                    if key not in place:
                        place[key] = int(hashlib.md5(key.encode()).hexdigest()[:8], 16) % dims
                    x[place[key]] += c
                out.append(x / max(1, len(code) - 1))
            yield pa.record_batch([b.column("row_id"), pa.array(out, pa.list_(pa.float64()))], ["row_id", "x"])

    rows = docs.filter("length(text) > 1").select(F.col("row_id").cast("long").alias("row_id"), F.lower("text").alias("low"))
    return rows.mapInArrow(shares, "row_id long, x array<double>")


@dataclass(frozen=True)
class Pca:
    """Leading directions of centred features, scaled by one global number, and a constant."""

    mean: np.ndarray
    directions: np.ndarray
    scale: float
    share: np.ndarray

    @staticmethod
    def fit(ex: DataFrame, width: int, k: int) -> Pca:
        """Second moments by one vector of sums per task; eigenvectors on the driver (width^2 numbers)."""
        n, total, square = moments(ex, width)
        mean = total / n
        values, vectors = np.linalg.eigh(square / n - np.outer(mean, mean))
        order = np.argsort(-values)[:k]
        lead = vectors[:, order] * np.sign(vectors[np.abs(vectors[:, order]).argmax(axis=0), order])
        return Pca(mean, lead, float(np.sqrt(max(values[order].mean(), 1e-12))), values[order] / values.sum())

    def apply(self, ex: DataFrame) -> DataFrame:
        """``x`` replaced by k components and a constant, in whole-stage expressions."""
        flat = F.array(*[F.array(*[F.lit(float(v)) for v in d]) for d in self.directions.T / self.scale])
        centred = F.zip_with("x", F.array(*[F.lit(float(v)) for v in self.mean]), lambda a, m: a - m)
        x = let(centred, lambda c: F.transform(flat, lambda w: dot(w, c)))
        return ex.withColumn("x", F.array_append(x, F.lit(1.0)))


def moments(ex: DataFrame, width: int) -> tuple[float, np.ndarray, np.ndarray]:
    """Rows, feature sums and X'X over the first ``width`` features; a task emits one vector."""

    def partial(batches):
        out = np.zeros((width + 1, width))
        n = 0
        for b in batches:
            if b.num_rows:
                x = np.asarray(b.column("x").flatten()).reshape(b.num_rows, -1)[:, :width]
                n += len(x)
                out[0] += x.sum(axis=0)
                out[1:] += x.T @ x
        yield pa.record_batch([pa.array([n]), pa.array([out.ravel()], pa.list_(pa.float64()))], ["n", "v"])

    parts = ex.select("x").mapInArrow(partial, "n long, v array<double>")
    n = parts.agg(F.sum("n")).first()[0] or 1
    sums = parts.select(F.posexplode("v").alias("i", "v")).groupBy("i").agg(F.sum("v").alias("v")).collect()
    flat = np.zeros((width + 1) * width)
    for r in sums:  # width (width + 1) rows
        flat[r["i"]] = r["v"]
    table = flat.reshape(width + 1, width)
    return float(n), table[0], table[1:]


def shard(ex: DataFrame, n: int, how: str = "iid", **o) -> DataFrame:
    """Add ``worker``: ``iid`` by hash, ``by_label`` in label order, ``by_key`` of a column,
    ``sizes`` by unequal quotas, ``dirichlet`` with per-label quotas."""
    seed = o.get("seed", SEED)
    if how == "iid":
        return ex.withColumn("worker", bucket(n, f"shard{seed}", "row_id"))
    if how == "by_key":
        return ex.withColumn("worker", bucket(n, f"key{seed}", o["key"]))
    if how == "by_label":
        total = ex.groupBy().count().first()[0]
        ranked = rank_within(
            ex.withColumn("_all", F.lit(0)).withColumn("_h", word("order", "row_id")),
            ["_all"], F.col("y") * 1024 + F.floor(F.col("_h") / (1 << 22)), ["y", "_h", "row_id"], "_r",
        )
        return ranked.withColumn("worker", F.floor((F.col("_r") - 1) * n / total).cast("int")).drop("_all", "_h", "_r")
    u = word(f"quota{seed}", "row_id") / float(1 << 32)
    if how == "sizes":
        whole, edge, pick = float(sum(o["sizes"])), 0.0, F.lit(n - 1)
        edges = []
        for i, s in enumerate(o["sizes"][:-1]):
            edge += s / whole
            edges.append((edge, i))
        for e, i in reversed(edges):
            pick = F.when(u < e, i).otherwise(pick)
        return ex.withColumn("worker", pick.cast("int"))
    if how == "dirichlet":
        cuts = dirichlet_cuts(o.get("alpha", 0.5), n, o["n_classes"], seed)
        table = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in cuts])
        mine = F.element_at(table, F.col("y") + 1)
        return ex.withColumn("worker", F.least(F.size(F.filter(mine, lambda c: c <= u)), F.lit(n - 1)).cast("int"))
    raise ValueError(f"no sharding {how}")


def assign_slots(ex: DataFrame, n_slots: int, seed: int = SEED) -> DataFrame:
    """Add ``slot``; iteration k reads slot (k - 1) mod n_slots: no replacement within a pass."""
    return ex.withColumn("slot", bucket(n_slots, f"slot{seed}", "row_id"))


def draw_batch(ex: DataFrame, k: int, m: int, seed: int = SEED, mode: str = "hash_rank", n_slots: int = 1) -> DataFrame:
    """The mini-batch of iteration k; a shard smaller than ``m`` is taken whole."""
    if mode == "full":
        return ex
    if mode == "epoch_slots":
        return ex.filter(F.col("slot") == (k - 1) % n_slots)
    if mode == "hash_rank":
        drawn = ex.withColumn("_h", word(f"batch{seed}", F.lit(k), "row_id"))
        order = W.partitionBy("worker").orderBy("_h", "row_id")
        return drawn.withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= m).drop("_h", "_r")
    raise ValueError(f"no batch mode {mode}")


def language(spark: SparkSession, sf_dir: str, letters: str = LETTERS, n: int = 6, how: str = "iid", **o) -> DataFrame:
    return shard(language_examples(load(spark, sf_dir, "documents"), letters), n, how, **o)
