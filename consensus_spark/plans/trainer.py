"""Training loops: relational (parameters stay DataFrames) and vectorised (small state).

Mini-batches are slots: a row's slot is a hash of its id, an iteration reads one slot, and
slots lie in directories of their own, so an iteration reads its batch and nothing else.
The vectorised loop fetches the batches of several iterations with one job where they fit
``PREFETCH_BYTES`` (a batch has a bounded number of rows, however large the table); a
larger batch is reduced to gradient sums in the tasks that read it.
"""

from __future__ import annotations

import os
import uuid
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from consensus_spark.functions.hashing import bucket
from consensus_spark.operators import mixing, timing, weights
from consensus_spark.operators.models import regulariser
from consensus_spark.operators.steps import value_at
from consensus_spark.operators.waiting import FullWait, Plan
from consensus_spark.plans.durable import cut, shared_dir
from consensus_spark.sources.tables import read_slot, save_slots

SMALL_STATE_BYTES = 256 << 20
PARTIAL_BYTES = 64 << 20
PREFETCH_BYTES = 64 << 20
#: Rows of a worker in a mini-batch, as in the experiments.
BATCH = 1024


@dataclass
class Config:
    """One run; ``order``: step_first or mix_first; ``late``: apply or discard; ``batch``: rows
    of a worker in an iteration (None: all of its shard)."""

    k_total: int
    n: int = 6
    step: str = "geometric"
    step_options: dict = field(default_factory=dict)
    order: str = "step_first"
    late: str = "apply"
    weights: str = "metropolis"
    eval_every: int = 10
    seed: int = 0
    batch: int | None = BATCH

    def step_at(self, k: int, on_time: set[int] | None = None) -> np.ndarray:
        """The step of every worker."""
        if self.step == "per_worker":
            return np.array([self.step_options["steps"][i] for i in range(self.n)])
        if self.step == "batch_proportional":
            part = self.n if on_time is None else len(on_time)
            return np.full(self.n, self.step_options["c"] * part / self.n)
        return np.full(self.n, value_at(self.step, k, **self.step_options))


def relational_train(spark: SparkSession, batch_of, plan: Plan, model, config: Config) -> DataFrame:
    """Parameters (worker, idx, val) after ``k_total`` iterations.

    ``batch_of(k)`` gives the mini-batch.  Every iteration is checkpointed: a chain of
    unmaterialised iterations would be planned and computed again at each use.
    """
    params = mixing.equal_start(spark, config.n, model.init(config.seed).tolist())
    active = plan.active.filter(F.col("k") <= config.k_total)
    times = plan.times.filter(F.col("k") <= config.k_total)
    table = cut(weights.weights_of(config.weights, active, times, config.n))
    ready = None
    if config.late == "discard":
        ready = times.join(plan.schedule.select("k", "cutoff"), "k").select("k", "worker", (F.col("t") <= F.col("cutoff")).alias("on_time"))
    for k in range(1, config.k_total + 1):
        w = table.filter(F.col("k") == k)
        grad = mixing.local_gradient(batch_of(k), params, model, config.n)
        step, l2 = float(config.step_at(k)[0]), getattr(model, "l2", 0.0)
        if config.order == "mix_first":
            params = mixing.combine_then_step(params, w, grad, step)
        else:
            takes = None if ready is None else ready.filter(F.col("k") == k)
            params = mixing.mix(mixing.half_step(params, grad, step, takes, l2), w)
        params = cut(params)
    return params


@dataclass
class Run:
    """State of one policy in the small regime: rows are workers."""

    name: str
    w: np.ndarray
    mats: dict[int, np.ndarray]
    duration: dict[int, float]
    backup: dict[int, float]
    on_time: dict[int, set[int]]


def _plan_tables(plan: Plan, config: Config) -> tuple[dict, dict, dict, dict]:
    """The control plane of the first iterations on the driver: K x (N + E) rows."""
    upto = F.col("k") <= config.k_total
    active, times = plan.active.filter(upto), plan.times.filter(upto)
    mats = weights.matrices(weights.weights_of(config.weights, active, times, config.n), config.n)
    duration = {r[0]: r[1] for r in timing.iteration_duration(active, times).collect()}
    degree = plan.edges.count()
    sent = {r[0]: r[1] for r in active.groupBy("k").count().collect()}
    backup = {k: (degree - sent.get(k, 0)) / config.n for k in duration}
    ready: dict[int, set[int]] = {}
    if (config.late == "discard" or config.step == "batch_proportional") and plan.schedule is not None:
        t = times.join(plan.schedule.filter(upto).select("k", "cutoff"), "k").filter("t <= cutoff")
        for r in t.select("k", "worker").collect():
            ready.setdefault(r[0], set()).add(r[1])
    return mats, duration, backup, ready


class Slots:
    """Training rows by slot on disk; an iteration reads one slot.

    Only the slots that a run of ``k_total`` iterations reads are written.
    """

    def __init__(self, train: DataFrame, config: Config, seed: int = 1):
        self.spark, self.n = train.sparkSession, config.n
        rows = train.count()
        self.count = 1 if config.batch is None else max(1, rows // (config.n * config.batch))
        self.per_slot = rows / self.count
        self.path = os.path.join(shared_dir(self.spark), f"slots-{uuid.uuid4().hex}")
        slot = train.withColumn("slot", bucket(self.count, f"slot{seed}", "row_id")).filter(F.col("slot") < config.k_total)
        save_slots(slot.select("slot", "worker", "x", "y"), self.path)
        self._held: dict[int, dict[int, tuple[np.ndarray, np.ndarray]]] = {}

    def of(self, k: int) -> int:
        return (k - 1) % self.count

    def frame(self, k: int) -> DataFrame:
        return read_slot(self.spark, self.path, self.of(k))

    def arrays(self, k: int, width: int) -> dict[int, tuple[np.ndarray, np.ndarray]] | None:
        """Features and labels of each worker's batch; None if a slot is too large to fetch."""
        s = self.of(k)
        if s not in self._held:
            most = int(PREFETCH_BYTES / max(1.0, self.per_slot * 8 * (width + 2)))
            if not most:
                return None
            upto = min(self.count, s + most)
            rows = self.spark.read.parquet(self.path).filter(F.col("slot").between(s, upto - 1))
            t = rows.select("slot", "worker", "x", "y").toArrow()
            slot, worker, y = (np.asarray(t.column(c)) for c in ("slot", "worker", "y"))
            x = np.asarray(t.column("x").combine_chunks().flatten()).reshape(len(y), -1)
            self._held = {}
            for i in range(s, upto):
                at = [np.flatnonzero((slot == i) & (worker == j)) for j in range(self.n)]
                self._held[i] = {j: (x[a], y[a]) for j, a in enumerate(at) if len(a)}
        return self._held[s]


_PARTIAL = "run int, worker int, n long, value array<double>"


def _gradients(batch: DataFrame, runs: list[Run], model, n: int) -> np.ndarray:
    """Mean gradient (run, worker, d) of one batch; all runs share its scan.

    A task sums over all its rows and emits one vector per run and worker.
    """
    states = [r.w for r in runs]
    size = model.size

    def partial(batches):
        total: dict[tuple[int, int], np.ndarray] = {}
        rows: dict[int, int] = {}
        for b in batches:
            if not b.num_rows:
                continue
            worker = np.asarray(b.column("worker"))
            x = np.asarray(b.column("x").flatten()).reshape(b.num_rows, -1)
            y = np.asarray(b.column("y"))
            for j in np.unique(worker).tolist():
                at = worker == j
                rows[j] = rows.get(j, 0) + int(at.sum())
                for i, w in enumerate(states):
                    total[i, j] = total.get((i, j), 0.0) + model.grad_sum(w[j], x[at], y[at])
        if total:
            run, own = zip(*total, strict=True)
            yield pa.record_batch(
                [pa.array(run, pa.int32()), pa.array(own, pa.int32()), pa.array([rows[j] for j in own], pa.int64()), pa.array(list(total.values()), pa.list_(pa.float64()))],
                ["run", "worker", "n", "value"],
            )

    parts = batch.select("worker", "x", "y").mapInArrow(partial, _PARTIAL)
    total, rows = np.zeros((len(runs), n, size)), np.zeros((len(runs), n))
    if batch.rdd.getNumPartitions() * len(runs) * n * size * 8 > PARTIAL_BYTES:
        long = parts.select("run", "worker", "n", F.posexplode("value").alias("idx", "g"))
        summed = long.groupBy("run", "worker", "idx").agg(F.sum("g").alias("g"), F.sum("n").alias("n"))
        for r in summed.toLocalIterator():  # run x worker x d numbers, checked by the caller
            total[r["run"], r["worker"], r["idx"]], rows[r["run"], r["worker"]] = r["g"], r["n"]
    else:
        for r in parts.collect():
            total[r["run"], r["worker"]] += r["value"]
            rows[r["run"], r["worker"]] += r["n"]
    return total / np.maximum(rows, 1)[:, :, None]


def _batch_gradients(slots: Slots, k: int, width: int, runs: list[Run], model, n: int) -> np.ndarray:
    held = slots.arrays(k, width)
    if held is None:
        return _gradients(slots.frame(k), runs, model, n)
    out = np.zeros((len(runs), n, model.size))
    for j, (x, y) in held.items():
        for i, r in enumerate(runs):
            out[i, j] = model.grad_sum(r.w[j], x, y) / len(y)
    return out


def _evaluate(ex: DataFrame, runs: list[Run], model) -> dict[int, tuple[float, float]]:
    """(training loss, test error) of each run's mean model, in one pass."""
    means = [r.w.mean(axis=0) for r in runs]

    def measure(batches):
        sums = np.zeros((len(means), 2))
        n = m = 0
        for b in batches:
            if not b.num_rows:
                continue
            x = np.asarray(b.column("x").flatten()).reshape(b.num_rows, -1)
            y, test = np.asarray(b.column("y")), np.asarray(b.column("is_test").to_pandas())
            n, m = n + int((~test).sum()), m + int(test.sum())
            for i, w in enumerate(means):
                if (~test).any():
                    sums[i, 0] += model.loss_sum(w, x[~test], y[~test])
                if test.any():
                    sums[i, 1] += (model.predict(w, x[test]) != y[test]).sum()
        if n + m:
            many = [len(means)]
            yield pa.record_batch(
                [pa.array(range(len(means)), pa.int32()), pa.array(sums[:, 0]), pa.array(np.repeat([n], many)), pa.array(sums[:, 1]), pa.array(np.repeat([m], many))],
                ["run", "loss", "n", "wrong", "m"],
            )

    sums = ex.select("x", "y", "is_test").mapInArrow(measure, "run int, loss double, n long, wrong double, m long")
    out = sums.groupBy("run").agg(*[F.sum(c).alias(c) for c in ("loss", "n", "wrong", "m")]).collect()
    penalty = [regulariser(w, getattr(model, "l2", 0.0))[0] for w in means]
    return {r["run"]: (r["loss"] / max(r["n"], 1) + penalty[r["run"]], r["wrong"] / max(r["m"], 1)) for r in out}


HISTORY = (
    "run string, k int, duration double, clock double, loss double, test_error double, "
    "disagreement double, mean_backup double"
)


def train_runs(spark: SparkSession, ex: DataFrame, plans: dict[str, Plan], model, config: Config, watch=None):
    """The runs after ``k_total`` iterations and their history rows.

    All policies share data, batches and times.  Needs N x d state within
    ``SMALL_STATE_BYTES``.  ``watch(k, runs, grads)`` sees every iteration.
    """
    if config.n * model.size * 8 * len(plans) > SMALL_STATE_BYTES:
        raise ValueError("state too large for the driver; use relational_train")
    ex = cut(ex.select("row_id", "worker", "x", "y", "is_test"))  # features are computed once
    slots = Slots(ex.filter("NOT is_test"), config)
    width = getattr(model, "n_features", 1)
    start = np.tile(model.init(config.seed), (config.n, 1))
    runs = [Run(name, start.copy(), *_plan_tables(plan, config)) for name, plan in plans.items()]
    clock, rows = [0.0] * len(runs), []
    for k in range(1, config.k_total + 1):
        grads = _batch_gradients(slots, k, width, runs, model, config.n)
        if watch:
            watch(k, runs, grads)
        for i, r in enumerate(runs):
            g = grads[i] + np.array([regulariser(w, getattr(model, "l2", 0.0))[1] for w in r.w])
            ready = r.on_time.get(k, set()) if r.on_time else None
            if config.late == "discard" and ready is not None:
                g = g * np.array([[w in ready] for w in range(config.n)])
            m, step = r.mats[k], config.step_at(k, ready)[:, None]
            r.w = m.T @ r.w - step * g if config.order == "mix_first" else m.T @ (r.w - step * g)
            clock[i] += r.duration[k]
        if k % config.eval_every == 0 or k in (1, config.k_total):
            seen = _evaluate(ex, runs, model)
            for i, r in enumerate(runs):
                spread = float(((r.w - r.w.mean(axis=0)) ** 2).sum(axis=1).max())
                rows.append((r.name, k, float(r.duration[k]), float(clock[i]), *map(float, seen[i]), spread, float(r.backup[k])))
    return runs, rows


def compare(spark: SparkSession, ex: DataFrame, plans: dict[str, Plan], model, config: Config) -> DataFrame:
    """History of every policy on the same data, batches and times."""
    return spark.createDataFrame(train_runs(spark, ex, plans, model, config)[1], HISTORY)


def trained(spark: SparkSession, ex: DataFrame, plan: Plan, model, config: Config) -> tuple[DataFrame, np.ndarray]:
    """Parameters of one run as rows (worker, idx, val), and as a matrix."""
    w = train_runs(spark, ex, {"run": plan}, model, config)[0][0].w
    rows = [(j, i, float(v)) for j, own in enumerate(w) for i, v in enumerate(own)]
    return spark.createDataFrame(rows, "worker int, idx int, val double"), w


def full_plan(times: DataFrame, edges: DataFrame) -> Plan:
    return FullWait().plan(times, edges)
