"""Queries on times, graphs, schedules, wait sets, weights and time measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from consensus_spark.operators import connectivity, timing, waiting, weights
from consensus_spark.operators.cover import find_cover
from consensus_spark.operators.schedule import clairvoyant_epochs, link_times, path_cover_schedule
from consensus_spark.operators.weights import rounded
from consensus_spark.plans import oracle as O
from consensus_spark.plans.durable import cut
from consensus_spark.sources import graphs, tables
from consensus_spark.sources.times import law, trace_from_events

N = 6
QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def trace(spark: SparkSession, sf_dir: str, n: int = N) -> DataFrame:
    return trace_from_events(tables.load(spark, sf_dir, "events"), n)


def six(spark: SparkSession) -> DataFrame:
    return graphs.edges(spark, graphs.SIX)


def early(spark: SparkSession, sf_dir: str, last: int | None) -> DataFrame:
    """The trace, or what a run of ``last`` iterations reads of it, ranked once."""
    t = trace(spark, sf_dir)
    return t if last is None else cut(t.filter(F.col("k") <= last))


def adaptive(spark: SparkSession, sf_dir: str, last: int | None = None, **options) -> waiting.Plan:
    return waiting.PathCover(graphs.SIX_COVER, **options).plan(early(spark, sf_dir, last), six(spark))


def full(spark: SparkSession, sf_dir: str, last: int | None = None) -> waiting.Plan:
    return waiting.FullWait().plan(early(spark, sf_dir, last), six(spark))


def with_times(sql: str) -> str:
    return f"WITH {O.times()} {sql}"


@query("t1_events_trace", with_times("SELECT k, worker, t FROM times"))
def _(spark, d):
    return trace(spark, d)


_U = "('0x' || substr(md5('{seed}|' || worker || '|' || k), 1, 8))::BIGINT / 4294967296.0"


def _law_sql(seed: str, value: str, n: int = 6, last: int = 500) -> str:
    grid = f"SELECT CAST(i // {n} + 1 AS INT) AS k, CAST(i % {n} AS INT) AS worker FROM range({n * last}) r(i)"
    return f"SELECT k, worker, round({value}, 6) AS t FROM (SELECT k, worker, {_U.format(seed=seed)} AS u FROM ({grid}))"


LAWS = {
    "t3_exponential_law": ("exponential", {}, "-ln(1 - u)"),
    "t4_shifted_exponential_law": ("shifted_exponential", {}, "1 - ln(1 - u)"),
    "t5_pareto_law": ("pareto", {}, "1 + pow(1 - u, -1 / 1.5)"),
    "t6_uniform_law": ("uniform", {}, "0.5 + u"),
    "t7_slow_one_law": ("slow_one", {"worker": 2}, "(0.5 + u) * CASE WHEN worker = 2 THEN 5.0 ELSE 1.0 END"),
    "t2_size_law": (
        "size_proportional", {"sizes": [1, 2, 3, 4, 5, 6]}, "(worker + 1) * (1 + 0.1 * (u - 0.5))",
    ),
}
for _name, (_kind, _p, _value) in LAWS.items():
    query(_name, _law_sql("7", _value))(
        lambda spark, d, k=_kind, p=_p: law(spark, k, 6, 500, 7, **p).withColumn("t", rounded("t"))
    )


def _uniform_sql(seed: str, key: str) -> str:
    return f"('0x' || substr(md5('{seed}|' || {key}), 1, 8))::BIGINT / 4294967296.0"


_WORKER_K = "worker || '|' || k"


def _times_sql(law_name: str, seed: int, last: int, n: int = N) -> str:
    """Compute times of a law, as a select of k, worker, t."""
    grid = f"SELECT CAST(i // {n} + 1 AS INT) AS k, CAST(i % {n} AS INT) AS worker FROM range({n * last}) r(i)"
    value = {
        "uniform": "0.5 + u", "exponential": "-ln(1 - u)", "shifted_exponential": "1 - ln(1 - u)", "pareto": "1 + pow(1 - u, -1 / 1.5)",
        "random_slow": f"(0.5 + u) * CASE WHEN {_uniform_sql(f'{seed}s', _WORKER_K)} < 0.1 THEN 10.0 ELSE 1.0 END",
        "slow_one": "(0.5 + u) * CASE WHEN worker = 0 THEN 5.0 ELSE 1.0 END",
        "one_random_slow": f"(0.5 + u) * CASE WHEN worker = floor({_uniform_sql(f'{seed}c', 'k')} * {n}) THEN 10.0 ELSE 1.0 END",
        "size_proportional": "[1.0, 1.1, 0.9, 1.05, 0.95, 1.0][worker + 1] * (1 + 0.1 * (u - 0.5))",
    }[law_name]
    return f"SELECT k, worker, {value} AS t FROM (SELECT k, worker, {_uniform_sql(seed, _WORKER_K)} AS u FROM ({grid}))"


@query("t8_random_slow_law", f"SELECT k, worker, round(t, 6) AS t FROM ({_times_sql('random_slow', 7, 500)})")
def _(spark, d):
    return law(spark, "random_slow", 6, 500, 7).withColumn("t", rounded("t"))


@query(
    "g_nation_region_edges",
    """WITH n AS (SELECT CAST(n_nationkey AS INT) id, CAST(n_regionkey AS INT) r FROM nation),
  h AS (SELECT min(id) id, row_number() OVER (ORDER BY min(id)) - 1 i, count(*) OVER () c FROM n GROUP BY r),
  ring AS (SELECT x.id a, y.id b FROM h x JOIN h y ON y.i = (x.i + 1) % x.c WHERE x.id <> y.id)
  SELECT x.id AS src, y.id AS dst FROM n x JOIN n y ON x.r = y.r AND x.id <> y.id
  UNION SELECT a, b FROM ring UNION SELECT b, a FROM ring""",
)
def _(spark, d):
    return graphs.nation_region_edges(tables.load(spark, d, "nation"))


def links_used(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The graph of the trace: links, in both directions, that were active in some iteration."""
    return adaptive(spark, sf_dir).active.select("src", "dst").distinct()


USED_SQL = f"{O.path_cover()}, used AS MATERIALIZED (SELECT DISTINCT src, dst FROM active)"


@query("g_degrees", f"{USED_SQL} SELECT dst AS worker, count(*) AS n_nbr FROM used GROUP BY dst")
def _(spark, d):
    """Neighbours with whom each worker exchanged parameters during the trace."""
    return links_used(spark, d).groupBy(F.col("dst").alias("worker")).agg(F.count(F.lit(1)).alias("n_nbr"))


@query(
    "g_reachable",
    f"""{USED_SQL}, reach AS (SELECT 0 AS worker, 0 AS hops UNION
  SELECT e.dst, r.hops + 1 FROM reach r JOIN used e ON e.src = r.worker WHERE r.hops < 6)
  SELECT CAST(worker AS INT) AS worker, CAST(min(hops) AS INT) AS hops FROM reach GROUP BY worker""",
)
def _(spark, d):
    """Hops from worker 0 over the links used; they are found once, not in every step."""
    cut(links_used(spark, d)).createOrReplaceTempView("links_used")
    return spark.sql(
        """WITH RECURSIVE reach(worker, hops) AS (SELECT 0, 0 UNION ALL
        SELECT e.dst, r.hops + 1 FROM reach r JOIN links_used e ON e.src = r.worker WHERE r.hops < 6)
        SELECT worker, min(hops) AS hops FROM reach GROUP BY worker"""
    )


_COVERS = "topology string, cover string, links int, connects boolean, path string, mean_time double"


@query("m10_covers")
def _(spark, d):
    """Covers of each kind on several topologies: links, how many, and their mean time on the trace."""
    pairs = graphs.graph("complete", N)
    per_link = link_times(trace(spark, d), pairs).groupBy("lid").agg(rounded(F.avg("c")).alias("c"))
    mean = {pairs[r["lid"]]: r["c"] for r in per_link.collect()}  # a row per pair of workers
    if not mean:
        return spark.createDataFrame([], _COVERS)
    rows = []
    for kind in ("random", "ring", "path", "star", "complete", "tree", "grid"):
        links = graphs.graph(kind, N, 3)
        for cover in ("hamiltonian", "tree", "walk", "min_time_tree"):
            c = find_cover(links, N, cover, 1, mean)
            rows.append((kind, cover, len(c), graphs.is_connected(c, N), str(c), round(sum(mean[x] for x in c) / len(c), 6)))
    return spark.createDataFrame(rows, _COVERS)


@query("m11_link_times", f"WITH {O.times()}, {O.cover_values()}, {O.LINKS} SELECT k, lid, c FROM lt")
def _(spark, d):
    return link_times(trace(spark, d), graphs.SIX_COVER)


_SCHEDULE = f"WITH RECURSIVE {O.times()}, {O.cover_values()}, {O.LINKS}, {O.schedule()} SELECT * FROM schedule"


@query("m11_schedule", _SCHEDULE)
def _(spark, d):
    return path_cover_schedule(trace(spark, d), graphs.SIX_COVER)


@query("m11_schedule_pandas", _SCHEDULE)
def _(spark, d):
    return path_cover_schedule(trace(spark, d), graphs.SIX_COVER, engine="pandas")


@query(
    "m11_schedule_warmup",
    f"""WITH RECURSIVE {O.times()}, {O.cover_values()}, {O.LINKS}, {O.schedule(5, 1)} SELECT * FROM schedule
  UNION ALL SELECT CAST(1 AS INT), CAST(0 AS INT), CAST(0 AS INT), CAST(-1 AS INT), max(t), CAST(0 AS INT) FROM times WHERE k = 1""",
)
def _(spark, d):
    return path_cover_schedule(trace(spark, d), graphs.SIX_COVER, warmup_full=True)


#: Needs ls, the links of each iteration by cost.
_TIES_ALL = """fold_all AS (
    SELECT CAST(0 AS INT) AS k, CAST(0 AS INT) AS epoch, CAST(0 AS INT) AS step, CAST(NULL AS INT) AS lid,
      CAST(NULL AS DOUBLE) AS cutoff, CAST(0 AS INT) AS n_tied, CAST([] AS INT[]) AS used, CAST([] AS INT[]) AS held
    UNION ALL
    SELECT k, epoch, CAST(step AS INT), free[1].lid, free[1].c, CAST(len(tied) AS INT),
      CASE WHEN len(held) + len(tied) = 5 THEN [] ELSE list_concat(held, tied) END, held
    FROM (SELECT s.k, CAST(CASE WHEN f.step > 0 AND len(f.used) = 0 THEN f.epoch + 1 ELSE f.epoch END AS INT) AS epoch,
        CASE WHEN len(f.used) = 0 THEN 1 ELSE f.step + 1 END AS step, f.used AS held,
        list_filter(s.links, lambda x: NOT list_contains(f.used, x.lid)) AS free,
        list_transform(list_filter(s.links, lambda x: NOT list_contains(f.used, x.lid) AND x.c =
          list_filter(s.links, lambda y: NOT list_contains(f.used, y.lid))[1].c), lambda x: x.lid) AS tied
      FROM fold_all f JOIN ls s ON s.k = f.k + 1) q)"""


@query(
    "m11_schedule_ties_all",
    f"""WITH RECURSIVE {O.times()}, {O.cover_values()}, {O.LINKS},
  ls AS (SELECT k, list(struct_pack(c := c, lid := lid) ORDER BY c, lid) AS links FROM lt GROUP BY k),
  {_TIES_ALL}
  SELECT k, epoch, step, lid, cutoff, n_tied FROM fold_all WHERE k > 0""",
)
def _(spark, d):
    return path_cover_schedule(trace(spark, d), graphs.SIX_COVER, ties="all")


GOLDEN_TIMES = [(1, 4, 2, 3), (2, 2, 5, 1), (6, 3, 1, 2)]


def golden(spark) -> DataFrame:
    rows = [(k + 1, w, float(t)) for k, r in enumerate(GOLDEN_TIMES) for w, t in enumerate(r)]
    return spark.createDataFrame(rows, tables.TIMES)


@query(
    "m11_golden",
    f"WITH RECURSIVE {O.times(4)}, {O.cover_values(graphs.FOUR_COVER)}, {O.LINKS}, {O.schedule(3)} SELECT * FROM schedule",
)
def _(spark, d):
    """The graph of the worked example on the trace of four workers; its hand-checked rows are a test."""
    return path_cover_schedule(trace(spark, d, 4), graphs.FOUR_COVER)


@query("m20_greedy_ratio")
def _(spark, d):
    """Cost of each epoch under the rule against the two clairvoyant plans."""
    t = trace(spark, d)
    own = path_cover_schedule(t, graphs.SIX_COVER).groupBy("epoch").agg(F.sum("cutoff").alias("rule"))
    one = clairvoyant_epochs(t, graphs.SIX_COVER).withColumnRenamed("cost", "one_link_each")
    free = clairvoyant_epochs(t, graphs.SIX_COVER, "free").withColumnRenamed("cost", "free")
    return own.join(one, "epoch").join(free, "epoch").withColumn("greedy_ratio", F.col("rule") / F.col("one_link_each"))


@query("m12_on_time", f"{O.path_cover()} SELECT t.k, t.worker, t.t, t.t <= s.cutoff AS on_time FROM times t JOIN schedule s USING (k)")
def _(spark, d):
    t = trace(spark, d)
    return waiting.on_time(t, path_cover_schedule(t, graphs.SIX_COVER))


@query("m12_active_edges", f"{O.path_cover()} SELECT k, src, dst FROM active")
def _(spark, d):
    return adaptive(spark, d).active


@query("m12_wait_counts", f"""{O.path_cover()} SELECT t.k, t.worker, t.t <= s.cutoff AS on_time, CAST(g.n AS INT) AS n_nbr,
  CAST(coalesce(a.n, 0) AS INT) AS n_wait, CAST(g.n - coalesce(a.n, 0) AS INT) AS n_backup FROM times t JOIN schedule s USING (k)
  JOIN (SELECT dst, count(*) n FROM edges GROUP BY dst) g ON g.dst = t.worker
  LEFT JOIN (SELECT k, dst, count(*) n FROM active GROUP BY k, dst) a ON a.k = t.k AND a.dst = t.worker""")
def _(spark, d):
    return adaptive(spark, d).wait().select("k", "worker", "on_time", "n_nbr", "n_wait", "n_backup")


@query("b01_full", f"{O.full_wait()} SELECT k, src, dst FROM active")
def _(spark, d):
    return full(spark, d).active


_RANKED = """ranked AS (SELECT t.k, e.src, e.dst, row_number() OVER (PARTITION BY t.k, e.dst ORDER BY t.t, e.src) r
  FROM times t JOIN edges e ON e.src = t.worker)"""
_COUNTS = {
    "b04_fastest1": (1, "receiver", "SELECT k, src, dst FROM ranked WHERE r <= 1"),
    "b04_fastest2_mutual": (
        2, "mutual",
        "SELECT x.k, x.src, x.dst FROM ranked x JOIN ranked y ON y.k = x.k AND y.src = x.dst AND y.dst = x.src WHERE x.r <= 2 AND y.r <= 2",
    ),
    "b04_fastest2_union": (
        2, "union", "SELECT k, src, dst FROM ranked WHERE r <= 2 UNION SELECT k, dst, src FROM ranked WHERE r <= 2",
    ),
}
for _name, (_q, _sym, _sql) in _COUNTS.items():
    query(_name, f"WITH {O.times()}, {O.edge_values()}, {_RANKED} {_sql}")(
        lambda spark, d, q=_q, s=_sym: waiting.FastestCount(q, s).plan(trace(spark, d), six(spark)).active
    )


@query(
    "b05_fixed_cutoff",
    f"WITH {O.times()}, {O.edge_values()}, schedule AS (SELECT DISTINCT k, 40.0::DOUBLE AS cutoff FROM times), {O.ACTIVE} SELECT k, src, dst FROM active",
)
def _(spark, d):
    return waiting.FixedCutoff(40.0).plan(trace(spark, d), six(spark)).active


@query(
    "b06_quantile_cutoff",
    f"WITH {O.times()}, {O.edge_values()}, schedule AS (SELECT k, quantile_cont(t, 0.5) AS cutoff FROM times GROUP BY k), {O.ACTIVE} SELECT k, src, dst FROM active",
)
def _(spark, d):
    return waiting.QuantileCutoff(0.5).plan(trace(spark, d), six(spark)).active


@query(
    "b07_server_sync",
    with_times("SELECT k, max(t) AS duration, count(*) AS server_messages, 2 * (count(*) - 1) AS ring_rounds FROM times GROUP BY k"),
)
def _(spark, d):
    return trace(spark, d).groupBy("k").agg(
        F.max("t").alias("duration"), F.count(F.lit(1)).alias("server_messages"),
        (2 * (F.count(F.lit(1)) - 1)).alias("ring_rounds"),
    )


@query(
    "b08_server_backup",
    with_times("SELECT k, worker, t, row_number() OVER (PARTITION BY k ORDER BY t, worker) <= 4 AS on_time FROM times"),
)
def _(spark, d):
    return waiting.ServerBackup(2).taken(trace(spark, d))


@query("m13_metropolis", f"{O.path_cover()}, {O.METROPOLIS} SELECT k, src, dst, round(w, 6) AS w FROM mix")
def _(spark, d):
    p = adaptive(spark, d)
    return weights.metropolis(p.active, p.times).withColumn("w", rounded("w"))


@query("m13_static", f"{O.full_wait()}, {O.METROPOLIS} SELECT src, dst, round(w, 6) AS w FROM mix WHERE k = 1")
def _(spark, d):
    p = full(spark, d)
    return weights.metropolis(p.active.filter("k = 1"), p.times.filter("k = 1")).select("src", "dst", rounded("w").alias("w"))


@query(
    "m13_receiver_mean",
    f"""WITH {O.times()}, {O.edge_values()}, {_RANKED}, active AS (SELECT k, src, dst FROM ranked WHERE r <= 1),
  offd AS (SELECT k, src, dst, 0.5::DOUBLE AS w FROM active)
  SELECT k, src, dst, w FROM offd UNION ALL SELECT k, worker, worker, 0.5::DOUBLE FROM times""",
)
def _(spark, d):
    p = waiting.FastestCount(1, "receiver").plan(trace(spark, d), six(spark))
    return weights.receiver_mean(p.active, p.times)


@query(
    "m13_max_degree",
    f"""{O.path_cover()}, deg AS (SELECT k, max(n) q FROM (SELECT k, dst, count(*) n FROM active GROUP BY k, dst) GROUP BY k),
  offd AS (SELECT a.k, a.src, a.dst, 1.0::DOUBLE / (1 + q) AS w FROM active a JOIN deg USING (k))
  SELECT k, src, dst, round(w, 6) AS w FROM offd UNION ALL SELECT t.k, t.worker, t.worker,
  round(1 - coalesce((SELECT sum(w) FROM offd o WHERE o.k = t.k AND o.dst = t.worker), 0), 6) FROM times t""",
)
def _(spark, d):
    p = adaptive(spark, d)
    return weights.max_degree(p.active, p.times).withColumn("w", rounded("w"))


@query(
    "a21_stochasticity",
    f"""{O.path_cover()}, {O.METROPOLIS} SELECT d.k, round(d.x, 6) AS dst_deviation, round(s.x, 6) AS src_deviation, round(d.m, 6) AS least
  FROM (SELECT k, max(abs(s - 1)) x, min(m) m FROM (SELECT k, dst, sum(w) s, min(w) m FROM mix GROUP BY k, dst) GROUP BY k) d
  JOIN (SELECT k, max(abs(s - 1)) x FROM (SELECT k, src, sum(w) s FROM mix GROUP BY k, src) GROUP BY k) s USING (k)""",
)
def _(spark, d):
    p = adaptive(spark, d)
    s = weights.stochasticity(weights.metropolis(p.active, p.times))
    return s.select("k", *[rounded(c).alias(c) for c in ("dst_deviation", "src_deviation", "least")])


@query("a20_smallest_weight", f"{O.path_cover()}, {O.METROPOLIS} SELECT round(min(w), 6) AS beta FROM mix WHERE w > 1e-12")
def _(spark, d):
    p = adaptive(spark, d)
    m = weights.metropolis(p.active, p.times).filter("w > 1e-12")
    return weights.smallest_weight(m).select(rounded("beta").alias("beta"))


@query(
    "m17_product3",
    f"""{O.path_cover()}, {O.METROPOLIS}, p2 AS (SELECT a.src, b.dst, sum(a.w * b.w) w FROM mix a JOIN mix b ON a.dst = b.src
  WHERE a.k = 1 AND b.k = 2 GROUP BY a.src, b.dst) SELECT a.src, b.dst, round(sum(a.w * b.w), 6) AS w FROM p2 a JOIN mix b ON a.dst = b.src
  WHERE b.k = 3 GROUP BY a.src, b.dst""",
)
def _(spark, d):
    p = adaptive(spark, d)
    m = weights.metropolis(p.active, p.times).filter("k <= 3")
    return weights.mix_product(m, 1, 3).select("src", "dst", rounded("w").alias("w"))


_DUR = O.DURATION.format(a="active")


@query("a03_duration", f"{O.path_cover()} {_DUR}")
def _(spark, d):
    p = adaptive(spark, d)
    return timing.iteration_duration(p.active, p.times)


@query("a03_duration_full", f"{O.full_wait()} {_DUR}")
def _(spark, d):
    p = full(spark, d)
    return timing.iteration_duration(p.active, p.times)


@query(
    "a04_worker_wait",
    f"""{O.path_cover()} SELECT t.k, t.worker, (SELECT max(s.t) FROM active a JOIN times s ON s.k = a.k AND s.worker = a.src
  WHERE a.k = t.k AND a.dst = t.worker) AS wait FROM times t""",
)
def _(spark, d):
    p = adaptive(spark, d)
    return timing.worker_wait(p.active, p.times)


@query("a05_estimate", f"{O.path_cover()} SELECT round(avg(duration), 6) AS estimate, round(var_pop(duration), 4) AS mse FROM ({_DUR})")
def _(spark, d):
    p = adaptive(spark, d)
    e = timing.duration_estimate(timing.iteration_duration(p.active, p.times))
    return e.select(rounded("estimate").alias("estimate"), rounded("mse", 4).alias("mse"))


_BOTH = f"""{O.path_cover()}, fulld AS (SELECT k, max(t) AS f FROM times GROUP BY k), both_ AS (SELECT k, duration AS o, f FROM ({_DUR}) JOIN fulld USING (k))"""


@query(
    "a06_reduction",
    f"""{_BOTH} SELECT round(1 - avg(o) / avg(f), 6) AS reduction, round(avg(1 - o / f), 6) AS mean_ratio_reduction,
  round(quantile_cont(1 - o / f, 0.5), 6) AS median_ratio_reduction FROM both_""",
)
def _(spark, d):
    a, f = adaptive(spark, d), full(spark, d)
    r = timing.duration_reduction(timing.iteration_duration(f.active, f.times), timing.iteration_duration(a.active, a.times))
    return r.select(*[rounded(c).alias(c) for c in r.columns])


@query("a07_clock", f"{O.path_cover()} SELECT k, duration, round(sum(duration) OVER (ORDER BY k), 4) AS clock FROM ({_DUR})")
def _(spark, d):
    p = adaptive(spark, d)
    return timing.clock(timing.iteration_duration(p.active, p.times)).withColumn("clock", rounded("clock", 4))


@query(
    "a24_dominance",
    f"{_BOTH} SELECT bool_and(f >= o) AS holds, count(*) AS iterations, CAST(sum(CAST(f > o AS INT)) AS BIGINT) AS strictly FROM both_",
)
def _(spark, d):
    a, f = adaptive(spark, d), full(spark, d)
    return timing.dominance(timing.iteration_duration(f.active, f.times), timing.iteration_duration(a.active, a.times))


_BACK = """SELECT t.k, t.worker, CAST(g.n - coalesce(a.n, 0) AS INT) AS n_backup FROM times t
  JOIN (SELECT dst, count(*) n FROM edges GROUP BY dst) g ON g.dst = t.worker
  LEFT JOIN (SELECT k, dst, count(*) n FROM active GROUP BY k, dst) a ON a.k = t.k AND a.dst = t.worker"""


@query("a08_backups", f"{O.path_cover()} {_BACK}")
def _(spark, d):
    return adaptive(spark, d).wait().select("k", "worker", "n_backup")


@query("a08_backup_mean", f"{O.path_cover()} SELECT k, round(avg(n_backup), 6) AS mean_backup FROM ({_BACK}) GROUP BY k")
def _(spark, d):
    return timing.backup_mean(adaptive(spark, d).wait()).withColumn("mean_backup", rounded("mean_backup"))


@query("w12_backup_panel", f"""{O.path_cover()} SELECT k, round(avg(n_backup), 6) AS mean_backup,
  round(avg(avg(n_backup)) OVER (), 6) AS run_mean FROM ({_BACK}) GROUP BY k""")
def _(spark, d):
    """Backup count per iteration with the run's mean line."""
    per = timing.backup_mean(adaptive(spark, d).wait())
    line = per.agg(F.avg("mean_backup").alias("run_mean"))
    return per.join(F.broadcast(line), F.lit(True)).select("k", rounded("mean_backup").alias("mean_backup"), rounded("run_mean").alias("run_mean"))


@query(
    "a29_participation",
    f"{O.path_cover()} SELECT worker, round(avg(CAST(t <= cutoff AS DOUBLE)), 6) AS share FROM times JOIN schedule USING (k) GROUP BY worker",
)
def _(spark, d):
    p = adaptive(spark, d)
    return timing.participation(p.schedule, p.times).withColumn("share", rounded("share"))


@query(
    "a25_messages",
    f"""{O.path_cover()} SELECT k, CAST(sum(m) AS BIGINT) AS messages, CAST(sum(m) * 8 * 152 AS BIGINT) AS bytes, max(m) AS busiest
  FROM (SELECT k, dst, count(*) m FROM active GROUP BY k, dst) GROUP BY k""",
)
def _(spark, d):
    return timing.messages(adaptive(spark, d).active, 152)


@query(
    "a26_control",
    """WITH u AS (SELECT user_id, count(*) AS m FROM events WHERE value IS NOT NULL AND user_id IS NOT NULL GROUP BY user_id),
  w AS (SELECT n, user_id % n AS worker, sum(m) AS m FROM u, range(2, 27) r(n) GROUP BY n, user_id % n),
  l AS (SELECT n, CASE WHEN count(*) = n THEN min(m) ELSE 0 END AS last FROM w GROUP BY n)
  SELECT CAST(n AS INT) AS n, CAST(n - 1 AS INT) AS d, CAST(2 * n AS INT) AS per_iteration, CAST(2 * n * (n - 1) AS INT) AS per_epoch,
    CAST(n - 1 AS INT) AS memory_links, CAST(last AS BIGINT) AS iterations, CAST(2 * n * last AS BIGINT) AS messages FROM l""",
)
def _(spark, d):
    """Control messages over the trace of n workers, n from 2 to 26; users are counted once for all n."""
    n = F.col("n")
    users = tables.load(spark, d, "events").filter("value IS NOT NULL AND user_id IS NOT NULL").groupBy("user_id").agg(F.count(F.lit(1)).alias("m"))
    dealt = users.select(F.explode(F.sequence(F.lit(2), F.lit(26))).alias("n"), "user_id", "m")
    held = dealt.groupBy("n", (F.col("user_id") % n).alias("worker")).agg(F.sum("m").alias("m"))
    last = held.groupBy("n").agg(F.when(F.count(F.lit(1)) == n, F.min("m")).otherwise(0).alias("iterations"))
    return last.select(
        "n", (n - 1).alias("d"), (2 * n).alias("per_iteration"), timing.control_overhead(n, n - 1).alias("per_epoch"),
        (n - 1).alias("memory_links"), "iterations", (2 * n * F.col("iterations")).alias("messages"),
    )


def _reach(n: int, width: int, mode: str) -> str:
    """Connected windows of the active edges in the CTE ``active``, by growing the set reached from worker 0."""
    name, aligned = f"{mode}{width}", mode == "aligned"
    place = f"(k - 1) // {width}" if aligned else f"unnest(range(greatest(1, k - {width} + 1), k + 1))"
    every = f"0, last // {width}" if aligned else f"1, last - {width} + 2"
    parts = [
        f"e{name} AS MATERIALIZED (SELECT DISTINCT w, src, dst FROM (SELECT {place} AS w, src, dst FROM active))",
        f"r{name}_0 AS (SELECT unnest(range({every})) AS w, 0 AS v FROM z)",
    ]
    for i in range(1, n):
        parts.append(f"r{name}_{i} AS MATERIALIZED (SELECT w, v FROM r{name}_{i - 1} UNION SELECT e.w, e.dst FROM e{name} e JOIN r{name}_{i - 1} r ON r.w = e.w AND r.v = e.src)")
    parts.append(f"c{name} AS (SELECT '{mode}' AS mode, {width} AS width, count(*) AS windows, CAST(sum(CAST(n = {n} AS INT)) AS BIGINT) AS connected FROM (SELECT w, count(*) AS n FROM r{name}_{n - 1} GROUP BY w))")
    return ", ".join(parts)


_A22 = (("aligned", 5), ("sliding", 5), ("sliding", 9))


@query(
    "a22_connectivity",
    f"{O.path_cover()}, z AS (SELECT max(k) AS last FROM times), " + ", ".join(_reach(N, w, m) for m, w in _A22)
    + " " + " UNION ALL ".join(f"SELECT * FROM c{m}{w}" for m, w in _A22),
)
def _(spark, d):
    """Aligned epochs, sliding windows of D and of 2D - 1: how many are connected."""
    p = adaptive(spark, d)
    last = p.times.agg(F.max("k")).first()[0] or 0
    parts = []
    for mode, w in (("aligned", 5), ("sliding", 5), ("sliding", 9)):
        c = connectivity.bounded_connectivity(p.active, N, last, w, mode)
        parts.append(
            c.groupBy().agg(F.count(F.lit(1)).alias("windows"), F.sum(F.col("connected").cast("long")).alias("connected"))
            .select(F.lit(mode).alias("mode"), F.lit(w).alias("width"), "windows", "connected")
        )
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


_A23 = (1, 2, 3, 6)
_PRODUCTS = f"""beta AS (SELECT min(w) AS b FROM mix WHERE w > 0), whole AS (SELECT max(k) // 5 AS n FROM times),
  prod AS (SELECT e.epochs, CAST(f AS INT) AS first, 0 AS step, CAST(s AS INT) AS src, CAST(d AS INT) AS dst, CASE WHEN s = d THEN 1.0 ELSE 0.0 END::DOUBLE AS v
    FROM (VALUES {', '.join(f'({n})' for n in _A23)}) e(epochs), (SELECT unnest(range(n)) AS f FROM whole), range(6) a(s), range(6) b(d) WHERE f <= (SELECT n FROM whole) - e.epochs
    UNION ALL SELECT p.epochs, p.first, p.step + 1, p.src, m.dst, sum(p.v * m.w) FROM prod p JOIN mix m ON m.k = p.first * 5 + p.step + 1 AND m.src = p.dst
    WHERE p.step < p.epochs * 5 GROUP BY p.epochs, p.first, p.step, p.src, m.dst)"""


@query(
    "a23_positivity",
    f"""{O.path_cover()}, {O.METROPOLIS.replace('mix AS (', 'mix AS MATERIALIZED (')}, {_PRODUCTS}
  SELECT CAST(epochs AS INT) AS epochs, first, round(CASE WHEN count(*) < 36 THEN 0.0 ELSE min(v) END, 8) AS least, round(pow(any_value(b), epochs * 5), 12) AS bound,
  count(*) = 36 AND min(v) > 0 AS positive FROM prod, beta WHERE step = epochs * 5 GROUP BY epochs, first""",
)
def _(spark, d):
    """Least entries of epoch products over all iterations against their bound."""
    p = adaptive(spark, d)
    m = dict(weights.in_order(weights.metropolis(p.active, p.times), N))
    rows = [(n, e, round(low, 8), round(bound, 12), low > 0) for n in _A23 for e, low, bound in connectivity.positivity(m, 5, n)]
    return spark.createDataFrame(rows, "epochs int, first int, least double, bound double, positive boolean")


@query("w11_duration_panel", f"""{_BOTH} SELECT b.k, b.f AS full_duration, b.o AS duration, round(m.mean_backup, 6) AS mean_backup
  FROM both_ b JOIN (SELECT k, avg(n_backup) AS mean_backup FROM ({_BACK}) GROUP BY k) m USING (k)""")
def _(spark, d):
    """Duration of every iteration under both rules, with its mean backup count."""
    a, f = adaptive(spark, d), full(spark, d)
    own = timing.iteration_duration(a.active, a.times)
    every = f.times.groupBy("k").agg(F.max("t").alias("full_duration"))
    back = timing.backup_mean(a.wait())
    return every.join(own, "k").join(back, "k").select("k", "full_duration", "duration", rounded("mean_backup").alias("mean_backup"))


_LAW_CASES = ("uniform", "exponential", "shifted_exponential", "pareto", "random_slow", "slow_one", "one_random_slow", "size_proportional")


def _law_reduction_sql(name: str) -> str:
    return f"""SELECT '{name}' AS law, (WITH RECURSIVE times AS MATERIALIZED ({_times_sql(name, 11, 500)}), {O.cover_values()}, {O.LINKS}, {O.schedule()},
    f AS (SELECT k, max(t) AS f FROM times GROUP BY k)
    SELECT round(1 - avg(s.cutoff) / avg(f.f), 6) FROM f JOIN schedule s USING (k)) AS reduction"""


@query("w11_law_reductions", " UNION ALL ".join(_law_reduction_sql(x) for x in _LAW_CASES))
def _(spark, d):
    """Mean duration cut of the rule under each compute-time law."""
    out, sizes = None, [1.0, 1.1, 0.9, 1.05, 0.95, 1.0]
    cases = [
        ("uniform", {}), ("exponential", {}), ("shifted_exponential", {}), ("pareto", {}), ("random_slow", {}),
        ("slow_one", {}), ("one_random_slow", {}), ("size_proportional", {"sizes": sizes}),
    ]
    for name, p in cases:
        t = law(spark, name, N, 500, 11, **p)
        s = path_cover_schedule(t, graphs.SIX_COVER).select("k", F.col("cutoff").alias("duration"))
        r = timing.duration_reduction(t.groupBy("k").agg(F.max("t").alias("duration")), s)
        r = r.select(F.lit(name).alias("law"), rounded("reduction").alias("reduction"))
        out = r if out is None else out.unionByName(r)
    return out


_KINDS = ("random", "ring", "path", "star", "complete", "grid", "tree", "regular")
_WINDOW = {kind: 2 * len(find_cover(graphs.graph(kind, N, 5), N)) - 1 for kind in _KINDS}


def _topology_sql(kind: str) -> str:
    links = graphs.graph(kind, N, 5)
    cover = find_cover(links, N)
    return f"""SELECT '{kind}' AS topology, (WITH RECURSIVE {O.edge_values(links)}, {O.cover_values(cover)}, {O.LINKS}, {O.schedule(len(cover))}, {O.ACTIVE},
    f AS (SELECT k, max(t) AS f FROM times GROUP BY k)
    SELECT struct_pack(reduction := (SELECT round(1 - avg(s.cutoff) / avg(f.f), 6) FROM f JOIN schedule s USING (k)),
      mean_backup := (SELECT round(avg(n_backup), 6) FROM ({_BACK}))) ) AS r"""


@query("w08_topologies", f"""WITH {O.times()} SELECT topology, r.reduction AS reduction, r.mean_backup AS mean_backup FROM ({' UNION ALL '.join(_topology_sql(x) for x in _KINDS)})""")
def _(spark, d):
    """Reduction and mean backups by topology on the six-worker trace."""
    t, out = cut(trace(spark, d)), None
    base = t.groupBy("k").agg(F.max("t").alias("duration"))
    for kind in _KINDS:
        links = graphs.graph(kind, N, 5)
        p = waiting.PathCover(find_cover(links, N)).plan(t, graphs.edges(spark, links))
        r = timing.duration_reduction(base, p.schedule.select("k", F.col("cutoff").alias("duration")))
        b = p.wait().agg(F.avg("n_backup").alias("mean_backup"))
        row = r.join(F.broadcast(b), F.lit(True)).select(
            F.lit(kind).alias("topology"), rounded("reduction").alias("reduction"), rounded("mean_backup").alias("mean_backup")
        )
        out = row if out is None else out.unionByName(row)
    return out


@query("w08_topology_connectivity")
def _(spark, d):
    """Share of connected windows (two covers less one long) by topology, six workers."""
    t, out = cut(trace(spark, d)), None
    last = t.agg(F.max("k")).first()[0] or 0
    for kind in _KINDS:
        links = graphs.graph(kind, N, 5)
        p = waiting.PathCover(find_cover(links, N)).plan(t, graphs.edges(spark, links))
        c = connectivity.bounded_connectivity(p.active, N, last, _WINDOW[kind], "sliding")
        row = c.agg(F.avg(F.col("connected").cast("double")).alias("share")).select(F.lit(kind).alias("topology"), F.lit(_WINDOW[kind]).alias("width"), "share")
        out = row if out is None else out.unionByName(row)
    return out


@query("w08_nation_region")
def _(spark, d):
    """Twenty-five workers on the graph of nations and regions: durations and backups."""
    edges = cut(graphs.nation_region_edges(tables.load(spark, d, "nation")))
    t = cut(trace(spark, d, 25))
    p = waiting.PathCover(find_cover(graphs.links_of(edges), 25, "tree")).plan(t, edges)
    base = t.groupBy("k").agg(F.max("t").alias("duration"))
    r = timing.duration_reduction(base, timing.iteration_duration(p.active, t))
    b = p.wait().agg(F.avg("n_backup").alias("mean_backup"), F.avg("n_nbr").alias("mean_degree"))
    return r.join(F.broadcast(b), F.lit(True)).select(rounded("reduction").alias("reduction"), rounded("mean_backup").alias("mean_backup"), rounded("mean_degree").alias("mean_degree"))


def _size(df: DataFrame, name: str) -> DataFrame:
    return df.agg(F.count(F.lit(1)).alias(name))


_POLICIES = ", ".join(
    f"('{name}', {edges})"
    for name, edges in (
        ("full", 16), ("path_cover", 16), ("path_cover_ties_all", 16), ("fastest1_mutual", 16), ("fastest2_mutual", 16),
        ("fastest2_union", 16), ("fixed_40", 16), ("median_cutoff", 16), ("server_backup2", 30), ("none", 16),
    )
)


@query(
    "w17_policies",
    f"""{O.path_cover()}, {_TIES_ALL}, {_RANKED},
  cuts AS (SELECT 'path_cover_ties_all' AS policy, k, cutoff FROM fold_all WHERE k > 0
    UNION ALL SELECT 'fixed_40', k, 40.0::DOUBLE FROM times GROUP BY k
    UNION ALL SELECT 'median_cutoff', k, quantile_cont(t, 0.5) FROM times GROUP BY k),
  taken AS (SELECT k, worker FROM times QUALIFY row_number() OVER (PARTITION BY k ORDER BY t, worker) <= 4),
  met AS (SELECT x.k, x.src, x.dst, greatest(x.r, y.r) AS r FROM ranked x JOIN ranked y ON y.k = x.k AND y.src = x.dst AND y.dst = x.src),
  waited AS (SELECT 'full' AS policy, t.k, e.src, e.dst FROM times t JOIN edges e ON e.src = t.worker
    UNION ALL SELECT 'path_cover', k, src, dst FROM active
    UNION ALL SELECT c.policy, x.k, e.src, e.dst FROM cuts c JOIN times x ON x.k = c.k JOIN edges e ON e.src = x.worker
      JOIN times y ON y.k = x.k AND y.worker = e.dst WHERE x.t <= c.cutoff AND y.t <= c.cutoff
    UNION ALL SELECT 'fastest1_mutual', k, src, dst FROM met WHERE r <= 1
    UNION ALL SELECT 'fastest2_mutual', k, src, dst FROM met WHERE r <= 2
    UNION ALL SELECT 'fastest2_union', * FROM (SELECT k, src, dst FROM ranked WHERE r <= 2 UNION SELECT k, dst, src FROM ranked WHERE r <= 2)
    UNION ALL SELECT 'server_backup2', x.k, x.worker, y.worker FROM taken x JOIN taken y ON y.k = x.k AND y.worker <> x.worker),
  per AS (SELECT w.policy, w.k, max(t.t) AS duration, count(*) AS n FROM waited w
    JOIN times t ON t.k = w.k AND t.worker = w.src GROUP BY w.policy, w.k),
  base AS (SELECT k, max(t) AS f FROM times GROUP BY k)
  SELECT p.policy, round(avg(coalesce(duration, 0)), 6) AS mean_duration, round(1 - avg(coalesce(duration, 0)) / avg(f), 6) AS reduction,
    round(max(p.n_edges) - avg(coalesce(n, 0)), 6) AS mean_backups
  FROM (VALUES {_POLICIES}) p(policy, n_edges) CROSS JOIN base b LEFT JOIN per x ON x.policy = p.policy AND x.k = b.k GROUP BY p.policy""",
)
def _(spark, d):
    """Every waiting policy on one trace: mean duration, its reduction, and mean backups of an iteration."""
    t, e, out = trace(spark, d), six(spark), None
    base = t.groupBy("k").agg(F.max("t").alias("duration"))
    policies = {
        "full": waiting.FullWait(), "path_cover": waiting.PathCover(graphs.SIX_COVER),
        "path_cover_ties_all": waiting.PathCover(graphs.SIX_COVER, ties="all"),
        "fastest1_mutual": waiting.FastestCount(1), "fastest2_mutual": waiting.FastestCount(2),
        "fastest2_union": waiting.FastestCount(2, "union"), "fixed_40": waiting.FixedCutoff(40.0),
        "median_cutoff": waiting.QuantileCutoff(0.5), "server_backup2": waiting.ServerBackup(2), "none": waiting.NoMixing(),
    }
    for name, policy in policies.items():
        p = policy.plan(t, e)
        dur = timing.iteration_duration(p.active, t)
        r = timing.duration_reduction(base, dur)
        m = timing.duration_estimate(dur)
        row = r
        for one in (m, _size(p.active, "kept"), _size(base, "n"), _size(p.edges, "edges")):  # one row each
            row = row.join(F.broadcast(one), F.lit(True))
        row = row.select(
            F.lit(name).alias("policy"), rounded("estimate").alias("mean_duration"), rounded("reduction").alias("reduction"),
            rounded(F.col("edges") - F.col("kept") / F.col("n")).alias("mean_backups"),
        )
        out = row if out is None else out.unionByName(row)
    return out
