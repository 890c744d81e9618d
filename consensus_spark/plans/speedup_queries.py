"""Speed-up by workers, time to a target, rates, and servers that do not wait, on least squares."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import functions as F

from consensus_spark.functions.hashing import bucket
from consensus_spark.operators import moments as M
from consensus_spark.operators import theory, timing, waiting, weights
from consensus_spark.operators.weights import rounded
from consensus_spark.plans import tasks
from consensus_spark.plans.durable import cut
from consensus_spark.plans.schedule_queries import N, trace
from consensus_spark.plans.training_queries import arrivals, word_sql
from consensus_spark.sources import graphs
from consensus_spark.sources.tables import load
from consensus_spark.sources.times import law

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
WIDTH, BATCHES, LAST = 5, 2400, 100
WORKERS = (2, 4, 6, 8, 12, 16, 25)
TARGET = 0.05


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def revenue_moments(spark, d) -> M.Moments:
    ex = tasks.revenue_examples(load(spark, d, "lineitem"), "regression").filter("NOT is_test")
    return M.Moments.fetch(M.batch_moments(ex.withColumn("batch", bucket(BATCHES, "mini1", "row_id")), WIDTH), BATCHES, WIDTH)


def ring(n: int) -> graphs.Links:
    return graphs.graph("ring", n)


def static_matrix(links, n: int) -> np.ndarray:
    """Metropolis weights of a graph on which everybody is waited for."""
    near = graphs.neighbours(links, n)
    m = np.zeros((n, n))
    for a, b in links:
        m[a, b] = m[b, a] = 1 / (1 + max(len(near[a]), len(near[b])))
    return m + np.diag(1 - m.sum(axis=1))


def step_of(n: int, last: int = LAST) -> float:
    """Proportional to the root of workers over iterations."""
    return math.sqrt(n / last)


# ---- DuckDB: the same recursion with workers of all sizes side by side -----------

_CELLS = [(n, a, b, v) for n in WORKERS for (a, b), v in np.ndenumerate(static_matrix(ring(n), n)) if v]
_RUN = f"""tr AS (SELECT [(l_quantity - 25.5) / 14.4, (l_extendedprice - 52500.0) / 30000.0, (l_discount - 0.05) / 0.03, (l_tax - 0.04) / 0.025, 1.0]::DOUBLE[] AS x,
    (l_extendedprice * (1 - l_discount) - 50000.0) / 30000.0 AS y, {word_sql('mini1', '(l_orderkey * 10 + l_linenumber)')} % {BATCHES} AS b
    FROM lineitem WHERE {word_sql('test', "(l_orderkey || '-' || l_linenumber)")} % 7 <> 0),
  bn AS MATERIALIZED (SELECT b, count(*) AS n FROM tr GROUP BY b),
  gr AS MATERIALIZED (SELECT b, i, j, sum(x[i] * x[j]) AS g FROM tr, range(1, {WIDTH + 1}) p(i), range(1, {WIDTH + 1}) q(j) GROUP BY b, i, j),
  xy AS MATERIALIZED (SELECT b, i, sum(x[i] * y) AS g FROM tr, range(1, {WIDTH + 1}) p(i) GROUP BY b, i),
  mix(n, src, dst, w) AS (VALUES {', '.join(f'({n}, {a}, {b}, {float(v)!r}::DOUBLE)' for n, a, b, v in _CELLS)}),
  steps(n, eta) AS (VALUES {', '.join(f'({n}, {step_of(n)!r}::DOUBLE)' for n in WORKERS)}),
  p AS (SELECT n, 0 AS k, CAST(w AS INT) AS worker, CAST(i AS INT) AS i, 0.0::DOUBLE AS v FROM steps, range(n) a(w), range(1, {WIDTH + 1}) d(i)
    UNION ALL
    SELECT h.n, h.k + 1, m.dst, h.i, sum(m.w * h.v) FROM (
      SELECT c.n, c.k, c.worker, c.i, any_value(c.v) - any_value(s.eta) * (sum(g.g * o.v) - any_value(xy.g)) / any_value(bn.n) AS v
      FROM p c JOIN steps s ON s.n = c.n
      JOIN gr g ON g.b = (c.k * c.n + c.worker) % {BATCHES} AND g.i = c.i JOIN p o ON o.n = c.n AND o.k = c.k AND o.worker = c.worker AND o.i = g.j
      JOIN xy ON xy.b = g.b AND xy.i = c.i JOIN bn ON bn.b = g.b WHERE c.k < {LAST} GROUP BY c.n, c.k, c.worker, c.i) h
    JOIN mix m ON m.n = h.n AND m.src = h.worker GROUP BY h.n, h.k, m.dst, h.i),
  mean AS (SELECT n, k, i, avg(v) AS v FROM p WHERE k > 0 GROUP BY n, k, i),
  tot AS (SELECT (SELECT sum(n) FROM bn) AS rows, (SELECT sum(y * y) FROM tr) AS yy),
  quad AS (SELECT a.n, a.k, sum(a.v * g.g * b.v) AS q FROM mean a JOIN (SELECT i, j, sum(g) AS g FROM gr GROUP BY i, j) g ON g.i = a.i
    JOIN mean b ON b.n = a.n AND b.k = a.k AND b.i = g.j GROUP BY a.n, a.k),
  lin AS (SELECT a.n, a.k, sum(a.v * x.g) AS l FROM mean a JOIN (SELECT i, sum(g) AS g FROM xy GROUP BY i) x ON x.i = a.i GROUP BY a.n, a.k),
  hist AS (SELECT CAST(n AS INT) AS n, CAST(k AS INT) AS k, 0.5 * (yy - 2 * l + q) / rows AS loss FROM quad JOIN lin USING (n, k), tot),
  tm AS (SELECT n, k, max(-ln(1 - u)) AS t FROM (SELECT s.n, k, ('0x' || substr(md5('3|' || w || '|' || k), 1, 8))::BIGINT / 4294967296.0 AS u
    FROM steps s, range(1, {LAST + 1}) r(k), range(n) a(w)) GROUP BY n, k),
  clk AS (SELECT n, k, sum(t) OVER (PARTITION BY n ORDER BY k) AS clock FROM tm)"""


def histories(spark, d, sizes=WORKERS):
    """Loss of the mean model and clock under full waiting on a ring: (n, k, loss, clock)."""
    m, rows = revenue_moments(spark, d), []
    for n in sizes:
        slow = law(spark, "exponential", n, LAST, 3).groupBy("k").agg(F.max("t").alias("t"))
        slowest, clock = {r["k"]: r["t"] for r in slow.collect()}, 0.0
        for k, w in M.synchronous(m, n, LAST, step_of(n), static_matrix(ring(n), n)):
            clock += slowest[k]
            rows.append((n, k, m.loss(w.mean(axis=0)), clock))
    return spark.createDataFrame(rows, "n int, k int, loss double, clock double")


@query("w09_worker_history", f"WITH RECURSIVE {_RUN} SELECT n, k, round(loss, 6) AS loss, round(clock, 4) AS clock FROM hist JOIN clk USING (n, k)")
def _(spark, d):
    """Least squares with 2 to 25 workers and batches of one size: loss and clock of every iteration."""
    return histories(spark, d).select("n", "k", rounded("loss").alias("loss"), rounded("clock", 4).alias("clock"))


_TO = f"""{_RUN}, to_ AS (SELECT n, CAST(min(CASE WHEN loss <= {TARGET} THEN k END) AS INT) AS k, min(CASE WHEN loss <= {TARGET} THEN clock END) AS clock
  FROM hist JOIN clk USING (n, k) GROUP BY n)"""


def reached(h):
    hit = F.col("loss") <= TARGET
    return h.groupBy("n").agg(F.min(F.when(hit, F.col("k"))).alias("k"), F.min(F.when(hit, F.col("clock"))).alias("clock"))


@query("a12_iterations_to", f"WITH RECURSIVE {_TO} SELECT n, k, round(clock, 4) AS clock FROM to_")
def _(spark, d):
    """First iteration and clock at which the loss is at the target, by number of workers."""
    return reached(histories(spark, d)).select("n", "k", rounded("clock", 4).alias("clock"))


@query("a13_speedup", f"WITH RECURSIVE {_TO} SELECT t.n, t.k, round(b.k / t.k::DOUBLE, 6) AS speedup, round(t.n / 2.0, 6)::DOUBLE AS linear FROM to_ t, to_ b WHERE b.n = 2")
def _(spark, d):
    """Iterations of the smallest number of workers over those of each, beside the linear law."""
    to = reached(histories(spark, d))
    base = to.filter("n = 2").select(F.col("k").alias("_b"))  # one row
    return to.join(F.broadcast(base), F.lit(True)).select(
        "n", "k", rounded(F.col("_b") / F.col("k")).alias("speedup"), rounded(F.col("n") / 2.0).alias("linear")
    )


@query("w09_speedup")
def _(spark, d):
    """Worker counts under both rules: iterations and clock to the target, speed-up, cut of the clock."""
    m, rows = revenue_moments(spark, d), []
    for n in WORKERS:
        links = ring(n)
        t = cut(law(spark, "exponential", n, LAST, 3))
        edges = graphs.edges(spark, links)
        plans = {"full": waiting.FullWait(), "adaptive": waiting.PathCover(graphs.graph("path", n))}
        for name, policy in plans.items():
            plan = policy.plan(t, edges)
            mats = weights.matrices(weights.metropolis(plan.active, t), n)
            spent = {r["k"]: r["clock"] for r in timing.clock(timing.iteration_duration(plan.active, t)).collect()}
            k = next((k for k, w in M.synchronous(m, n, LAST, step_of(n), mats) if m.loss(w.mean(axis=0)) <= TARGET), None)
            rows.append((name, n, k, spent.get(k)))
    h = spark.createDataFrame(rows, "run string, n int, k int, clock double")
    base = h.filter("n = 2").select("run", F.col("k").alias("_b"))
    return h.join(F.broadcast(base), "run").select("run", "n", "k", "clock", (F.col("_b") / F.col("k")).alias("speedup"))


@query("a14_rate_fit")
def _(spark, d):
    """Slope of log gap against log(N K): final gap of the averaged model over runs of all sizes."""
    m, rows = revenue_moments(spark, d), []
    least = m.loss(m.best())
    for n in WORKERS:
        for last in (50, 100, 200, 400):
            path = np.array([w.mean(axis=0) for _, w in M.synchronous(m, n, last, step_of(n, last), static_matrix(ring(n), n))])
            rows.append((n, last, m.loss(path.mean(axis=0)) - least))
    return theory.rate_fit(spark.createDataFrame(rows, "n int, k int, gap double"))


# ---- servers that do not wait ----------------------------------------------------


@query("b09_server_async_training")
def _(spark, d):
    """A server that applies every gradient on arrival: loss and mean staleness along the updates."""
    m = revenue_moments(spark, d)
    order = arrivals(trace(spark, d)).orderBy("version")
    seen, rows, late = ((r["worker"], r["k"]) for r in order.toLocalIterator()), [], 0
    for at, stale, w in M.asynchronous(m, seen, N, 0.05):
        late += stale
        if at % 100 == 0:
            rows.append((at, late / at, m.loss(w)))
    return spark.createDataFrame(rows, "updates int, mean_staleness double, loss double")


@query("b10_stale_sync_training")
def _(spark, d):
    """Bounded staleness: loss and clock along the iterations for bounds 0, 1 and 4."""
    m, rows = revenue_moments(spark, d), []
    steps = cut(trace(spark, d).groupBy("k").agg(F.array_sort(F.collect_list(F.struct("worker", "t"))).alias("ts")).orderBy("k"))
    for bound in (0, 1, 4):
        times = ((r["k"], [x["t"] for x in r["ts"]]) for r in steps.toLocalIterator())
        for k, clock, w in M.bounded_staleness(m, times, N, bound, 0.2):
            if k % 100 == 0:
                rows.append((bound, k, clock, m.loss(w)))
    return spark.createDataFrame(rows, "bound int, k int, clock double, loss double")
