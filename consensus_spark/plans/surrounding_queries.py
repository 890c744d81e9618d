"""Queries on joins, aggregates, windows, sets and streams around the methods."""

from __future__ import annotations

import uuid

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from consensus_spark.operators import timing, waiting
from consensus_spark.operators.cover import find_cover
from consensus_spark.operators.schedule import path_cover_schedule
from consensus_spark.operators.weights import rounded
from consensus_spark.plans import oracle as O
from consensus_spark.plans.durable import cut
from consensus_spark.plans.schedule_queries import USED_SQL, N, adaptive, links_used, six, trace
from consensus_spark.sources import graphs
from consensus_spark.sources.tables import EVENTS, load
from consensus_spark.streaming import completions as S

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


@query("o_semi_labelled", "SELECT doc_id, lang FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def _(spark, d):
    return load(spark, d, "documents").select("doc_id", "lang").join(load(spark, d, "labels").select("doc_id"), "doc_id", "left_semi")


@query("o_anti_unlabelled", "SELECT doc_id, lang FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def _(spark, d):
    return load(spark, d, "documents").select("doc_id", "lang").join(load(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


@query(
    "o_asof_params",
    """WITH p AS (SELECT ts, event_id AS version FROM events WHERE event_id % 50 = 0)
  SELECT e.event_id, max(p.version) AS version FROM events e LEFT JOIN p ON p.ts <= e.ts GROUP BY e.event_id""",
)
def _(spark, d):
    """Latest parameter version before each event: union and last value by day buckets."""
    e = load(spark, d, "events").select("event_id", "ts", F.when(F.col("event_id") % 50 == 0, F.col("event_id")).alias("v"))
    day = e.withColumn("day", F.date_trunc("day", "ts"))
    inside = W.partitionBy("day").orderBy("ts").rangeBetween(W.unboundedPreceding, 0)
    before = W.orderBy("day").rowsBetween(W.unboundedPreceding, -1)  # one row per day
    carried = day.groupBy("day").agg(F.max("v").alias("last")).select("day", F.max("last").over(before).alias("carried"))
    local = day.withColumn("local", F.max("v").over(inside))
    return local.join(carried, "day").select("event_id", F.coalesce("local", "carried").alias("version"))


@query(
    "o_range_iterations",
    f"""{O.path_cover()}, c AS (SELECT k, cutoff, sum(cutoff) OVER (ORDER BY k) AS hi FROM schedule)
  SELECT c.k, count(*) AS n FROM c JOIN events e ON e.value > c.hi - c.cutoff AND e.value <= c.hi GROUP BY c.k""",
)
def _(spark, d):
    """Events whose value falls in an iteration's stretch of the clock (interval join by buckets)."""
    s = path_cover_schedule(trace(spark, d), graphs.SIX_COVER).select("k", F.col("cutoff").alias("duration"))
    c = timing.clock(s).select("k", (F.col("clock") - F.col("duration")).alias("lo"), F.col("clock").alias("hi"))
    width = 50.0
    cells = c.withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    e = load(spark, d, "events").select("value", F.floor(F.col("value") / width).alias("cell"))
    return e.join(cells, "cell").filter("value > lo AND value <= hi").groupBy("k").agg(F.count(F.lit(1)).alias("n"))


_POLICY = """x AS (SELECT k % 4 AS phase, CASE WHEN t <= 40 THEN 'fast' ELSE 'slow' END AS speed, worker, t FROM times)"""
for _name, _how, _sql in (
    ("o_cube_sweep", "cube", "CUBE (phase, speed)"),
    ("o_rollup_history", "rollup", "ROLLUP (phase, speed)"),
):
    query(
        _name,
        f"WITH {O.times()}, {_POLICY} SELECT CAST(coalesce(phase, -1) AS INT) AS phase, coalesce(speed, 'all') AS speed, count(*) AS n, round(avg(t), 6) AS mean FROM x GROUP BY {_sql}",
    )(
        lambda spark, d, how=_how: getattr(
            trace(spark, d).select((F.col("k") % 4).alias("phase"), F.when(F.col("t") <= 40, "fast").otherwise("slow").alias("speed"), "t"), how
        )("phase", "speed").agg(F.count(F.lit(1)).alias("n"), rounded(F.avg("t")).alias("mean"))
        .select(F.coalesce("phase", F.lit(-1)).alias("phase"), F.coalesce("speed", F.lit("all")).alias("speed"), "n", "mean")
    )


@query(
    "o_grouping_sets",
    f"WITH {O.times()}, {_POLICY} SELECT CAST(coalesce(phase, -1) AS INT) AS phase, CAST(coalesce(worker, -1) AS INT) AS worker, count(*) AS n FROM x GROUP BY GROUPING SETS ((phase), (worker))",
)
def _(spark, d):
    trace(spark, d).select((F.col("k") % 4).alias("phase"), "worker").createOrReplaceTempView("sweep_rows")
    return spark.sql(
        "SELECT coalesce(phase, -1) AS phase, coalesce(worker, -1) AS worker, count(*) AS n FROM sweep_rows GROUP BY GROUPING SETS ((phase), (worker))"
    )


@query("o_topk_slowest", f"WITH {O.times()} SELECT k, worker, t FROM times ORDER BY t DESC, k, worker LIMIT 10")
def _(spark, d):
    return trace(spark, d).orderBy(F.desc("t"), "k", "worker").limit(10)


@query(
    "o_moving_average",
    f"{O.path_cover()} SELECT k, round(avg(cutoff) OVER (ORDER BY k ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 6) AS smooth FROM schedule",
)
def _(spark, d):
    s = path_cover_schedule(trace(spark, d), graphs.SIX_COVER).select("k", F.col("cutoff").alias("duration"))
    return timing.moving_average(s).select("k", rounded("smooth").alias("smooth"))


@query("o_json_props", "SELECT event_id, json_extract_string(props, '$.k') AS k_text FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")
def _(spark, d):
    return load(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k_text")).filter("k_text IS NOT NULL")


@query(
    "o_set_ops_links",
    f"""{USED_SQL} SELECT src, dst, 'off_cover' AS part FROM used WHERE src < dst EXCEPT SELECT a, b, 'off_cover' FROM cover
  UNION ALL (SELECT src, dst, 'on_cover' FROM used WHERE src < dst INTERSECT SELECT a, b, 'on_cover' FROM cover)""",
)
def _(spark, d):
    """Links used during the trace, off the cover and on it."""
    e = cut(links_used(spark, d)).filter("src < dst")
    c = graphs.link_table(spark, graphs.SIX_COVER).select(F.col("a").alias("src"), F.col("b").alias("dst"))
    return e.exceptAll(c).withColumn("part", F.lit("off_cover")).unionByName(e.intersect(c).withColumn("part", F.lit("on_cover")))


@query("o_distinct_counts", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY event_type")
def _(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count(F.lit(1)).alias("n"))


@query(
    "o_tumbling",
    "SELECT date_trunc('day', ts) AS day, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1",
)
def _(spark, d):
    e = load(spark, d, "events")
    return e.groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(F.count(F.lit(1)).alias("n"), rounded(F.sum("value"), 4).alias("total"))


def _event_stream(spark, d):
    """The events table, a file or a folder of them, as a replayed file stream."""
    return spark.readStream.schema(EVENTS).parquet(f"{d}/events.parque[t]")  # a stream takes a single file as a pattern only


def _name() -> str:
    return f"s{uuid.uuid4().hex}"


_SCHED = f"""WITH RECURSIVE {O.times()}, {O.edge_values()}, {O.cover_values()}, {O.LINKS}, {O.schedule()}, {O.ACTIVE}
  SELECT s.k, s.lid, s.cutoff, (SELECT CAST(count(*) AS INT) FROM times t WHERE t.k = s.k AND t.t <= s.cutoff) AS on_time,
  CAST(16 - (SELECT count(*) FROM active a WHERE a.k = s.k) AS INT) AS backups FROM schedule s"""


@query("o_stream_schedule", _SCHED)
def _(spark, d):
    """The stateful stream gives the batch schedule."""
    done = S.completions(_event_stream(spark, d), N)
    return S.replay(S.stream_path_cover(done, N, graphs.SIX, graphs.SIX_COVER), _name()).drop("run")


@query("o_stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def _(spark, d):
    s = _event_stream(spark, d).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
    twice = s.dropDuplicatesWithinWatermark(["event_id"])
    return S.replay(twice.select("event_id"), _name()).agg(F.count("event_id").alias("n"))


@query("o_sliding", """WITH w AS (SELECT unnest([time_bucket(INTERVAL '1 hour', ts), time_bucket(INTERVAL '1 hour', ts) - INTERVAL '1 hour']) AS start, value FROM events)
  SELECT start, count(*) AS n, CAST(sum(CAST(value > 100 AS INT)) AS BIGINT) AS slow FROM w GROUP BY start""")
def _(spark, d):
    """Straggler rate of sliding windows over the replayed stream."""
    return S.replay(S.straggler_rate(_event_stream(spark, d)), _name(), "complete").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "slow")


@query("o_session_heartbeats", f"""WITH e AS (SELECT CAST(user_id % {N} AS INT) AS worker, ts FROM events),
  g AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY worker ORDER BY ts) + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS fresh FROM e),
  s AS (SELECT *, sum(fresh) OVER (PARTITION BY worker ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g)
  SELECT worker, min(ts) AS start, max(ts) + INTERVAL '30 minutes' AS "end", count(*) AS n FROM s GROUP BY worker, session""")
def _(spark, d):
    return S.replay(S.heartbeats(_event_stream(spark, d), N), _name(), "complete").select(
        "worker", F.col("s.start").cast("timestamp_ntz").alias("start"), F.col("s.end").cast("timestamp_ntz").alias("end"), "n"
    )


def online_examples(events, n: int):
    """Type of the event one-hot and a constant; the target is the event's scaled value."""
    kinds = ("click", "purchase", "view", "signup", "error")
    x = F.array(*[(F.col("event_type") == k).cast("double") for k in kinds], F.lit(1.0))
    return events.filter("value IS NOT NULL").select((F.col("user_id") % n).cast("int").alias("worker"), x.alias("x"), (F.col("value") / 100).alias("y"), "value")


@query("w20_online")
def _(spark, d):
    """Online training: every micro-batch of the replayed stream is one iteration under the path cover.

    A worker's time is the mean value of its events in the batch; its gradient is taken over
    them.  Parameters and used links pass from batch to batch; a replayed batch counts once.
    """
    import numpy as np

    from consensus_spark.operators.models import LeastSquares
    from consensus_spark.plans.durable import shared_dir
    from consensus_spark.plans.trainer import Run, _gradients

    folder, model = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", LeastSquares(6)
    load(spark, d, "events").repartitionByRange(16, "ts").write.parquet(f"{folder}/in")
    run, used, rows = Run("online", np.zeros((N, model.size)), {}, {}, {}, {}), [], {}

    def one(batch, k):
        if k in rows:
            return
        ex = online_examples(batch, N)
        seen = {r["worker"]: r for r in ex.groupBy("worker").agg(F.avg("value").alias("t"), F.count(F.lit(1)).alias("n")).collect()}  # a row per worker
        if not seen:
            return
        grad = _gradients(ex, [run], model, N)[0]
        t = [seen[i]["t"] if i in seen else float("inf") for i in range(N)]
        cutoff, lid = min((max(t[a], t[b]), i) for i, (a, b) in enumerate(graphs.SIX_COVER) if i not in used)
        used.append(lid)
        if len(used) == len(graphs.SIX_COVER):
            used.clear()
        ready = [x <= cutoff for x in t]
        active = [(a, b) for a, b in graphs.SIX if ready[a] and ready[b]]
        near = graphs.neighbours(active, N)
        m = np.zeros((N, N))
        for a, b in active:
            m[a, b] = m[b, a] = 1 / (1 + max(len(near[a]), len(near[b])))
        m += np.diag(1 - m.sum(axis=1))
        run.w = m.T @ (run.w - 0.3 * grad)
        mean = run.w.mean(axis=0)
        rows[k] = (int(k) + 1, int(sum(r["n"] for r in seen.values())), float(cutoff), 2 * (len(graphs.SIX) - len(active)), float(np.linalg.norm(grad.mean(axis=0))), float(((run.w - mean) ** 2).sum(axis=1).max()))

    stream = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    q = stream.writeStream.foreachBatch(one).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.createDataFrame([rows[k] for k in sorted(rows)], "k int, n int, cutoff double, backups int, gradient_norm double, disagreement double")


@query("s_formats", f"WITH {O.times()} SELECT kind, count(*) AS n, round(sum(t), 4) AS total FROM times, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) f(kind) GROUP BY kind")
def _(spark, d):
    """The trace written and read again in every format, under its schema."""
    from consensus_spark.plans.durable import shared_dir
    from consensus_spark.sources.tables import TIMES, read_rows, write_rows

    t, out = cut(trace(spark, d)), None
    for kind in ("csv", "json", "orc", "parquet"):
        path = f"{shared_dir(spark)}/rows-{uuid.uuid4().hex}"
        write_rows(t, path, kind)
        part = read_rows(spark, path, kind, TIMES).agg(F.count(F.lit(1)).alias("n"), rounded(F.sum("t"), 4).alias("total")).withColumn("kind", F.lit(kind))
        out = part if out is None else out.unionByName(part)
    return out


@query("s_history", f"""{O.path_cover()}, a AS (SELECT 'adaptive' AS run, k, cutoff FROM schedule), f AS (SELECT 'full' AS run, k, max(t) AS cutoff FROM times GROUP BY k)
  SELECT run, count(*) AS n, round(sum(cutoff), 4) AS total FROM (SELECT * FROM a UNION ALL SELECT * FROM f) GROUP BY run""")
def _(spark, d):
    """Two runs appended to one history and read back run by run."""
    from consensus_spark.plans.durable import shared_dir
    from consensus_spark.sources.tables import append_history

    path, t = f"{shared_dir(spark)}/history-{uuid.uuid4().hex}", trace(spark, d)
    for name, plan in (("adaptive", waiting.PathCover(graphs.SIX_COVER)), ("full", waiting.FullWait())):
        append_history(plan.plan(t, six(spark)).schedule.select("k", "cutoff").withColumn("run", F.lit(name)), path)
    read = lambda name: spark.read.parquet(path).filter(F.col("run") == name)
    both = read("adaptive").unionByName(read("full"))
    return both.groupBy("run").agg(F.count(F.lit(1)).alias("n"), rounded(F.sum("cutoff"), 4).alias("total"))


@query("u_sql_functions", f"""WITH {O.edge_values()}, q AS (SELECT dst AS w, count(*) AS n FROM edges GROUP BY dst)
  SELECT e.src, e.dst, round(1.0 / (1 + greatest(x.n, y.n)), 9)::DOUBLE AS weight, round(0.2 * pow(0.95, e.src), 9) AS step, (e.src * e.dst + 2.0)::DOUBLE AS dot
  FROM edges e JOIN q x ON x.w = e.src JOIN q y ON y.w = e.dst""")
def _(spark, d):
    """Registered SQL functions in SQL text."""
    from consensus_spark.functions.registered import register

    register(spark)
    six(spark).createOrReplaceTempView("six_edges")
    return spark.sql(
        """WITH q AS (SELECT dst AS w, count(*) AS n FROM six_edges GROUP BY dst)
        SELECT e.src, e.dst, round(metropolis_weight(x.n, y.n), 9) AS weight, round(geometric_step(e.src), 9) AS step,
          vector_dot(array(CAST(e.src AS DOUBLE), 1D), array(CAST(e.dst AS DOUBLE), 2D)) AS dot
        FROM six_edges e JOIN q x ON x.w = e.src JOIN q y ON y.w = e.dst"""
    )


@query("u_pandas_functions", f"""{O.path_cover()} SELECT t.k, round(sum(greatest(t.t - s.cutoff, 0)), 6) AS late, round(max(t.t) - min(t.t), 6) AS spread
  FROM times t JOIN schedule s USING (k) GROUP BY t.k""")
def _(spark, d):
    """A pandas scalar and a pandas aggregate function over the schedule."""
    from consensus_spark.functions.registered import excess, spread

    p = adaptive(spark, d)
    t = p.times.join(p.schedule.select("k", "cutoff"), "k")
    late = t.select("k", excess("t", "cutoff").alias("e")).groupBy("k").agg(rounded(F.sum("e")).alias("late"))
    return late.join(t.groupBy("k").agg(F.round(spread("t"), 6).alias("spread")), "k")


@query("u_cover_table", f"WITH {O.values('c', 'lid, a, b', [(i, a, b) for i, (a, b) in enumerate(find_cover(graphs.graph('grid', 6, 5), 6))])} SELECT lid, a, b FROM c")
def _(spark, d):
    """A cover as a table function in SQL text."""
    from consensus_spark.functions.registered import register

    register(spark)
    return spark.sql("SELECT lid, a, b FROM cover_links('grid', 6)")


@query("o_outer_compare", f"""{O.path_cover()} SELECT coalesce(a.k, b.k) AS k, a.cutoff AS adaptive, b.m AS other FROM schedule a
  FULL JOIN (SELECT k + 5 AS k, max(t) AS m FROM times GROUP BY k) b ON b.k = a.k""")
def _(spark, d):
    """Full outer comparison of two runs with different iterations."""
    p = adaptive(spark, d)
    a = p.schedule.select("k", F.col("cutoff").alias("adaptive"))
    b = waiting.FullWait().plan(p.times, p.edges).schedule.select((F.col("k") + 5).alias("k"), F.col("cutoff").alias("other"))
    return a.join(b, "k", "full")
