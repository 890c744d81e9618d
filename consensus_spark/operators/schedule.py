"""The path-cover rule: cutoffs of all iterations as a relational fold.

Nothing in the schedule depends on parameters or gradients, and epochs are
independent, so all iterations are planned at once: one shuffle by epoch, a fold
over the epoch's steps inside an expression, no user function.
"""

from __future__ import annotations

import itertools
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from consensus_spark.sources.graphs import Links

_ROW = "struct<k:int,epoch:int,step:int,lid:int,cutoff:double,n_tied:int>"
SCHEDULE = "k int, epoch int, step int, lid int, cutoff double, n_tied int"


def times_by_iteration(times: DataFrame) -> DataFrame:
    """One row per iteration: ``at[worker]``."""
    packed = F.array_sort(F.collect_list(F.struct("worker", "t")))
    return times.groupBy("k").agg(F.transform(packed, lambda x: x["t"]).alias("at"))


def _link_array(cover: Links, at: Column) -> Column:
    links = F.array(*[F.struct(F.lit(i).alias("lid"), F.lit(a).alias("a"), F.lit(b).alias("b")) for i, (a, b) in enumerate(cover)])
    later = lambda x: F.greatest(F.get(at, x["a"]), F.get(at, x["b"]))
    return F.transform(links, lambda x: F.struct(later(x).alias("c"), x["lid"].alias("lid")))


def link_times(times: DataFrame, cover: Links) -> DataFrame:
    """When each cover link has both ends finished: ``k``, ``lid``, ``c``."""
    by_k = times_by_iteration(times)
    return by_k.select("k", F.inline(_link_array(cover, F.col("at")))).select("k", "lid", "c")


def path_cover_schedule(
    times: DataFrame, cover: Links, ties: str = "one", warmup_full: bool = False, engine: str = "fold"
) -> DataFrame:
    """Cutoff of every iteration: the earliest moment an unused cover link is complete.

    ``ties="one"`` marks the lowest link of those complete at that moment, so an epoch
    has as many iterations as the cover has links and epochs fold in parallel;
    ``ties="all"`` marks all of them, so epochs end early and one run is folded in
    order.  ``warmup_full`` lets iteration 1 wait for everyone, before epoch 1.
    """
    if ties not in ("one", "all"):
        raise ValueError("ties is 'one' or 'all'")
    by_k = times_by_iteration(times)
    if not cover:
        return by_k.select("k", (F.col("k") - 1).alias("epoch"), F.lit(1).alias("step"), F.lit(-1).alias("lid"), F.lit(0.0).alias("cutoff"), F.lit(0).alias("n_tied"))
    if ties == "all":
        return _all_ties(by_k, cover, warmup_full)
    d, shift = len(cover), int(warmup_full)
    steps = by_k.filter(F.col("k") > shift).select(
        "k",
        (F.floor((F.col("k") - 1 - shift) / d) + shift).cast("int").alias("epoch"),
        ((F.col("k") - 1 - shift) % d + 1).cast("int").alias("step"),
        _link_array(cover, F.col("at")).alias("links"),
    )
    if engine == "pandas":
        out = steps.groupBy("epoch").applyInPandas(_fold_pandas, SCHEDULE)
    else:
        epochs = steps.groupBy("epoch").agg(F.array_sort(F.collect_list(F.struct("step", "k", "links"))).alias("steps"))
        out = epochs.select(F.inline(_fold(F.col("steps"), F.col("epoch"))))
    if warmup_full:
        first = by_k.filter("k = 1").select(
            "k", F.lit(0).alias("epoch"), F.lit(0).alias("step"), F.lit(-1).alias("lid"),
            F.array_max("at").alias("cutoff"), F.lit(0).alias("n_tied"),
        )
        out = out.unionByName(first)
    return out


def _fold(steps: Column, epoch: Column) -> Column:
    start = F.struct(F.array().cast("array<int>").alias("used"), F.array().cast(f"array<{_ROW}>").alias("out"))

    def merge(acc: Column, s: Column) -> Column:
        free = F.filter(s["links"], lambda x: ~F.array_contains(acc["used"], x["lid"]))
        best = F.array_min(free)
        row = F.struct(
            s["k"].alias("k"), epoch.alias("epoch"), s["step"].alias("step"), best["lid"].alias("lid"),
            best["c"].alias("cutoff"), F.size(F.filter(free, lambda x: x["c"] == best["c"])).alias("n_tied"),
        )
        return F.struct(
            F.array_append(acc["used"], best["lid"]).alias("used"), F.array_append(acc["out"], row).cast(f"array<{_ROW}>").alias("out")
        )

    return F.aggregate(steps, start, merge, lambda acc: acc["out"])


def _fold_pandas(epoch: pd.DataFrame) -> pd.DataFrame:
    used, rows = set(), []
    for r in epoch.sort_values("step").itertuples():
        free = [(x["c"], x["lid"]) for x in r.links if x["lid"] not in used]
        c, lid = min(free)
        used.add(lid)
        rows.append((r.k, r.epoch, r.step, lid, c, sum(x[0] == c for x in free)))
    return pd.DataFrame(rows, columns=["k", "epoch", "step", "lid", "cutoff", "n_tied"])


def _all_ties(by_k: DataFrame, cover: Links, warmup_full: bool) -> DataFrame:
    """One run in order: the state (used links, epoch, step) passes from iteration to iteration."""
    d = len(cover)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        used: set[int] = set()
        epoch, step, rows = int(warmup_full), 0, []
        for r in pdf.sort_values("k").itertuples():
            if warmup_full and r.k == 1:
                rows.append((r.k, 0, 0, -1, max(r.at), 0))
                continue
            at = [(max(r.at[a], r.at[b]), i) for i, (a, b) in enumerate(cover) if i not in used]
            c, lid = min(at)
            tied = [i for x, i in at if x == c]
            used.update(tied)
            step += 1
            rows.append((r.k, epoch, step, lid, c, len(tied)))
            if len(used) == d:
                used, epoch, step = set(), epoch + 1, 0
        return pd.DataFrame(rows, columns=["k", "epoch", "step", "lid", "cutoff", "n_tied"])

    return by_k.withColumn("run", F.lit(0)).groupBy("run").applyInPandas(run, SCHEDULE)


def clairvoyant_cost(table: list[list[float]], mode: str) -> float:
    """Least total cutoff of one epoch when all times are known.

    ``table[step][link]`` is when the link completes.  ``one_link_each`` assigns the
    links to steps one to one; ``free`` lets a step cover any set, at its latest link.
    """
    d = len(table[0]) if table else 0
    if mode == "one_link_each":

        @lru_cache(None)
        def best(step: int, left: int) -> float:
            if step == len(table) or not left:
                return 0.0
            return min(table[step][i] + best(step + 1, left & ~(1 << i)) for i in range(d) if left >> i & 1)

        return best(0, (1 << d) - 1)
    if mode != "free":
        raise ValueError(f"no mode {mode}")

    @lru_cache(None)
    def least(step: int, left: int) -> float:
        if not left:
            return 0.0
        if step == len(table):
            return float("inf")
        out, sub = least(step + 1, left), left
        while sub:
            out = min(out, max(table[step][i] for i in range(d) if sub >> i & 1) + least(step + 1, left & ~sub))
            sub = (sub - 1) & left
        return out

    return least(0, (1 << d) - 1)


def clairvoyant_epochs(times: DataFrame, cover: Links, mode: str = "one_link_each") -> DataFrame:
    """``epoch``, ``cost``, of whole epochs."""
    d = len(cover)
    steps = times_by_iteration(times).select(
        F.floor((F.col("k") - 1) / d).cast("int").alias("epoch"), "k", _link_array(cover, F.col("at")).alias("links")
    )

    def cost(pdf: pd.DataFrame) -> pd.DataFrame:
        table = [[x["c"] for x in sorted(r, key=lambda x: x["lid"])] for r in pdf.sort_values("k")["links"]]
        value = clairvoyant_cost(table, mode) if len(table) == d else None
        return pd.DataFrame({"epoch": [pdf["epoch"].iloc[0]], "cost": [value]})

    return steps.groupBy("epoch").applyInPandas(cost, "epoch int, cost double").filter("cost IS NOT NULL")


def exact_min_wait(table: list[list[float]], links: Links, n: int, window: int) -> float:
    """Least total cutoff such that every ``window`` successive unions connect all workers.

    ``table[k][worker]``; enumerates cutoffs, for tiny inputs only.
    """
    from consensus_spark.sources.graphs import is_connected

    best = float("inf")
    for cut in itertools.product(*[[0.0, *sorted(set(r))] for r in table]):
        if sum(cut) >= best:
            continue
        active = [[(a, b) for a, b in links if r[a] <= c and r[b] <= c] for r, c in zip(table, cut, strict=True)]
        if all(is_connected(sum(active[i : i + window], []), n) for i in range(len(table) - window + 1)):
            best = sum(cut)
    return best
