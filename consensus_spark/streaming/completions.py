"""The path-cover rule on a stream of worker completions.

One key is one run; its state is who has finished in the open iteration, the used
links and the step: O(workers + links).  A run is sequential by nature; streams scale
out over runs.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from consensus_spark.plans.durable import shared_dir
from consensus_spark.sources.graphs import Links

_STATE = "k int, open string, used string"
_OUT = "run int, k int, lid int, cutoff double, on_time int, backups int"
_LAST = np.iinfo(np.int64).max
_ROWS = 100_000  # handed to Spark at once


def completions(events: DataFrame, n: int) -> DataFrame:
    """Events as completions: run, worker, time, in arrival order; events without a value are none."""
    return events.filter("value IS NOT NULL AND user_id IS NOT NULL").select(
        F.lit(0).alias("run"), (F.col("user_id") % n).cast("int").alias("worker"), F.col("value").alias("t"), "ts", "event_id"
    )


def _queues(waiting: list[list[float]], frames: Iterator[pd.DataFrame]) -> list[np.ndarray]:
    """Times of each worker in arrival order, behind those that wait; its own copies end with it."""
    parts = [(f["worker"].to_numpy(np.int16), f["t"].to_numpy(copy=True), f["ts"].to_numpy(copy=True), f["event_id"].to_numpy(copy=True)) for f in frames]
    worker, t, ts, event = (np.concatenate(x) for x in zip(*parts, strict=True))
    del parts
    order = np.lexsort((event, ts))  # rows without a ts come last
    worker, t = worker[order], t[order]
    return [np.concatenate([np.array(q, float), t[worker == i]]) for i, q in enumerate(waiting)]


def _in_order(x: np.ndarray) -> np.ndarray:
    """Integers that compare as the numbers do in Spark: NaN after all others, zeros equal."""
    bits = np.where(np.isnan(x), np.nan, x + 0.0).view(np.int64)
    return np.where(bits < 0, bits ^ _LAST, bits)


def _pick(cost: np.ndarray, used: list[int]) -> tuple[np.ndarray, list[int]]:
    """The link of each iteration, and those used in the epoch left open.

    ``cost[iteration, link]``; ``used`` was marked in the open epoch before.  An epoch has an
    iteration per link, so the same step of all epochs is taken at once.
    """
    m, d = cost.shape
    table = np.full((-(-(len(used) + m) // d) * d, d), _LAST)
    table[len(used) : len(used) + m] = cost
    table = table.reshape(-1, d, d)
    marked, epochs = np.zeros((len(table), d), bool), np.arange(len(table))
    lid = np.empty((len(table), d), np.int64)
    for step in range(d):
        lid[:, step] = np.where(marked, _LAST, table[:, step]).argmin(axis=1)
        if step < len(used):
            lid[0, step] = used[step]
        marked[epochs, lid[:, step]] = True
    flat, end = lid.reshape(-1), len(used) + m
    return flat[len(used) : end], flat[end - end % d : end].tolist()


def stream_path_cover(done: DataFrame, n: int, links: Links, cover: Links) -> DataFrame:
    """Emit each iteration's cutoff once all its workers' times are known to the replay.

    Completions of a worker queue up by arrival; iteration k takes the k-th of each.
    A worker past the cutoff is late: its edges are backups.
    """

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        k, waiting, used = (state.get if state.exists else (0, json.dumps([[] for _ in range(n)]), "[]"))
        queue = _queues(json.loads(waiting), frames)
        m = min(map(len, queue))
        if m:
            times = np.stack([q[:m] for q in queue], axis=1)
            at = _in_order(times)
            cost = np.stack([np.maximum(at[:, a], at[:, b]) for a, b in cover], axis=1)
            lid, marked = _pick(cost, json.loads(used))
            used = json.dumps(marked)
            cutoff = cost[np.arange(m), lid]
            a, b = np.array(cover)[lid].T
            row = np.arange(m)
            later = np.where(at[row, a] >= at[row, b], times[row, a], times[row, b])
            ready = at <= cutoff[:, None]
            active = sum(2 * (ready[:, a] & ready[:, b]).astype(int) for a, b in links)
            out = pd.DataFrame(
                {"run": key[0], "k": k + 1 + row, "lid": lid, "cutoff": later, "on_time": ready.sum(axis=1), "backups": 2 * len(links) - active}
            )
            k += m
            yield from (out[i : i + _ROWS] for i in range(0, m, _ROWS))
        state.update((k, json.dumps([q[m:].tolist() for q in queue]), used))

    return done.groupBy("run").applyInPandasWithState(step, _OUT, _STATE, "append", GroupStateTimeout.NoTimeout)


def straggler_rate(events: DataFrame, limit: float = 100.0) -> DataFrame:
    """Share of slow completions per sliding window, late rows dropped by the watermark."""
    return (
        events.withColumn("ts", F.col("ts").cast("timestamp"))
        .withWatermark("ts", "10 minutes")
        .groupBy(F.window("ts", "2 hours", "1 hour").alias("w"))
        .agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("value") > limit).cast("long")).alias("slow"))
    )


def heartbeats(events: DataFrame, n: int, gap: str = "30 minutes") -> DataFrame:
    """Sessions of each worker: runs of events without a longer pause."""
    return (
        events.withColumn("ts", F.col("ts").cast("timestamp"))
        .withWatermark("ts", "10 minutes")
        .groupBy(F.session_window("ts", gap).alias("s"), (F.col("user_id") % n).cast("int").alias("worker"))
        .agg(F.count(F.lit(1)).alias("n"))
    )


def replay(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a replayed file stream to its end and return the rows.

    Appended rows grow with the stream and go to Parquet in the shared folder; a
    complete result is one row per group and is kept in memory.
    """
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/stream-{name}"
    out = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/state")
    if mode == "complete":
        out.format("memory").queryName(name).start().awaitTermination()
        return spark.table(name)
    out.format("parquet").start(f"{path}/rows").awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")
