"""Waiting policies: who mixes with whom in each iteration.

Every policy gives a ``Plan``: the active edges (k, src, dst), dst waiting for src,
and the cutoff of each iteration where there is one.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from consensus_spark.operators.schedule import path_cover_schedule
from consensus_spark.sources.graphs import Links


@dataclass
class Plan:
    """``schedule`` holds (k, cutoff) at least; ``None`` where the policy has no cutoff."""

    times: DataFrame
    edges: DataFrame
    active: DataFrame
    schedule: DataFrame | None = None

    def wait(self) -> DataFrame:
        return wait_sets(self.times, self.edges, self.active, self.schedule)


def full_active(times: DataFrame, edges: DataFrame) -> DataFrame:
    """Every neighbour, every iteration."""
    return times.select("k", "worker").join(F.broadcast(edges), F.col("worker") == F.col("src")).select("k", "src", "dst")


def on_time(times: DataFrame, schedule: DataFrame) -> DataFrame:
    """``k``, ``worker``, ``t``, ``on_time``."""
    return times.join(schedule.select("k", "cutoff"), "k").select(
        "k", "worker", "t", (F.col("t") <= F.col("cutoff")).alias("on_time")
    )


def cutoff_active(times: DataFrame, edges: DataFrame, schedule: DataFrame) -> DataFrame:
    """Edges whose both ends finished by the cutoff; a late worker mixes with nobody."""
    ready = on_time(times, schedule).filter("on_time").groupBy("k").agg(F.collect_set("worker").alias("ready"))
    graph = edges.agg(F.array_sort(F.collect_list(F.struct("src", "dst"))).alias("graph"))  # one row, the static graph
    pairs = F.filter("graph", lambda e: F.array_contains("ready", e["src"]) & F.array_contains("ready", e["dst"]))
    return ready.join(F.broadcast(graph), F.lit(True)).select("k", F.inline(pairs))


def fastest_active(times: DataFrame, edges: DataFrame, q: int, symmetrise: str = "mutual") -> DataFrame:
    """Each worker waits for its ``q`` fastest neighbours (ties by worker).

    ``mutual`` keeps an edge both ends chose, ``union`` one that either chose,
    ``receiver`` leaves the choice one-sided (its weights then do not keep the mean).
    """
    reached = times.join(F.broadcast(edges), F.col("worker") == F.col("src")).select("k", "src", "dst", "t")
    order = W.partitionBy("k", "dst").orderBy("t", "src")
    chosen = reached.withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= q).select("k", "src", "dst")
    if symmetrise == "receiver":
        return chosen
    back = chosen.select("k", F.col("dst").alias("src"), F.col("src").alias("dst"))
    if symmetrise == "mutual":
        return chosen.join(back, ["k", "src", "dst"])
    if symmetrise == "union":
        return chosen.unionByName(back).distinct()
    raise ValueError("symmetrise is 'mutual', 'union' or 'receiver'")


@dataclass(frozen=True)
class PathCover:
    cover: Links
    ties: str = "one"
    warmup_full: bool = False

    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        s = path_cover_schedule(times, list(self.cover), self.ties, self.warmup_full)
        return Plan(times, edges, cutoff_active(times, edges, s), s)


@dataclass(frozen=True)
class FullWait:
    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        s = times.groupBy("k").agg(F.max("t").alias("cutoff"))
        return Plan(times, edges, full_active(times, edges), s)


@dataclass(frozen=True)
class FastestCount:
    q: int
    symmetrise: str = "mutual"

    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        return Plan(times, edges, fastest_active(times, edges, self.q, self.symmetrise))


@dataclass(frozen=True)
class FixedCutoff:
    cutoff: float

    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        s = times.select("k").distinct().withColumn("cutoff", F.lit(float(self.cutoff)))
        return Plan(times, edges, cutoff_active(times, edges, s), s)


@dataclass(frozen=True)
class QuantileCutoff:
    p: float

    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        s = times.groupBy("k").agg(F.percentile("t", F.lit(self.p)).alias("cutoff"))
        return Plan(times, edges, cutoff_active(times, edges, s), s)


def complete(times: DataFrame) -> DataFrame:
    """Edges of the graph a server stands for: every worker hears of every other."""
    w = times.agg(F.collect_set("worker").alias("all"))
    return w.select("all", F.explode("all").alias("src")).select("src", F.explode("all").alias("dst")).filter("src <> dst")


@dataclass(frozen=True)
class ServerSync:
    """Exact averaging by a server or ring: everyone hears of everyone."""

    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        a, b = times.select("k", F.col("worker").alias("src")), times.select("k", F.col("worker").alias("dst"))
        s = times.groupBy("k").agg(F.max("t").alias("cutoff"))
        return Plan(times, complete(times), a.join(b, "k").filter("src <> dst").select("k", "src", "dst"), s)


@dataclass(frozen=True)
class ServerBackup:
    """The server takes the first N - b gradients."""

    b: int

    def taken(self, times: DataFrame) -> DataFrame:
        n = F.count(F.lit(1)).over(W.partitionBy("k"))
        place = F.row_number().over(W.partitionBy("k").orderBy("t", "worker"))
        return times.select("k", "worker", "t", (place <= n - self.b).alias("on_time"))

    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        ready = self.taken(times).filter("on_time")
        a, b = ready.select("k", F.col("worker").alias("src")), ready.select("k", F.col("worker").alias("dst"))
        s = ready.groupBy("k").agg(F.max("t").alias("cutoff"))
        return Plan(times, complete(times), a.join(b, "k").filter("src <> dst").select("k", "src", "dst"), s)


@dataclass(frozen=True)
class NoMixing:
    def plan(self, times: DataFrame, edges: DataFrame) -> Plan:
        return Plan(times, edges, full_active(times, edges).filter("false"))


def wait_sets(times: DataFrame, edges: DataFrame, active: DataFrame, schedule: DataFrame | None = None) -> DataFrame:
    """Per worker and iteration: who is waited for, who is a backup, and how many."""
    degree = edges.groupBy(F.col("dst").alias("worker")).agg(F.array_sort(F.collect_list("src")).alias("near"))
    waits = active.groupBy("k", F.col("dst").alias("worker")).agg(F.array_sort(F.collect_list("src")).alias("waits"))
    out = (
        times.join(F.broadcast(degree), "worker", "left")
        .join(waits, ["k", "worker"], "left")
        .select(
            "k", "worker", "t",
            F.coalesce("near", F.array().cast("array<int>")).alias("near"),
            F.coalesce("waits", F.array().cast("array<int>")).alias("waits"),
        )
        .withColumn("backups", F.array_except("near", "waits"))
    )
    late = F.lit(None).cast("boolean")
    if schedule is not None:
        out = out.join(schedule.select("k", "cutoff"), "k", "left")
        late = F.col("t") <= F.col("cutoff")
    return out.select(
        "k", "worker", late.alias("on_time"), "waits", "backups",
        F.size("near").alias("n_nbr"), F.size("waits").alias("n_wait"), F.size("backups").alias("n_backup"),
    )
