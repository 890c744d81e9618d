"""Queries on shards, features, training, accuracy and theory."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from consensus_spark.functions.prefix import rank_within
from consensus_spark.operators import mixing, quality, steps, tail, theory, timing, waiting, weights
from consensus_spark.operators.models import LeastSquares, Quadratic, Softmax, least_squares_optimum
from consensus_spark.operators.weights import rounded
from consensus_spark.plans import oracle as O
from consensus_spark.plans import tasks
from consensus_spark.plans.schedule_queries import N, adaptive, early, full, six, trace
from consensus_spark.plans.durable import cut
from consensus_spark.plans.trainer import Config, Slots, compare, relational_train, train_runs, trained
from consensus_spark.sources import graphs
from consensus_spark.sources.tables import load

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


# ---- DuckDB parts -------------------------------------------------------------


def word_sql(seed: str, key: str) -> str:
    return f"('0x' || substr(md5('{seed}|' || {key}), 1, 8))::BIGINT"


def language_sql(letters: str) -> str:
    part = ", ".join(
        f"((length(lower(text))::DOUBLE - length(replace(lower(text), '{c}', ''))) / length(lower(text))::DOUBLE - {tasks.CENTRE}) * {tasks.SCALE}"
        for c in letters
    )
    return f"""ex AS (SELECT doc_id AS row_id, [{part}, 1.0]::DOUBLE[] AS x,
    CAST(list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS INT) AS y, {word_sql('test', 'doc_id')} % 7 = 0 AS is_test,
    CAST({word_sql('shard1', 'doc_id')} % 6 AS INT) AS worker FROM documents WHERE length(text) > 0)"""


TIER_SQL = f"""ex AS (SELECT row_number() OVER () AS row_id,
    [(l_quantity - 25.5) / 14.4, (l_extendedprice - 52500.0) / 30000.0, (l_discount - 0.05) / 0.03, (l_tax - 0.04) / 0.025, 1.0]::DOUBLE[] AS x,
    CAST(CASE WHEN l_extendedprice * (1 - l_discount) < 33800 THEN 0 WHEN l_extendedprice * (1 - l_discount) < 66800 THEN 1 ELSE 2 END AS INT) AS y,
    (l_extendedprice * (1 - l_discount) - 50000.0) / 30000.0 AS target,
    {word_sql('test', "(l_orderkey || '-' || l_linenumber)")} % 7 = 0 AS is_test,
    CAST({word_sql('shard1', '(l_orderkey * 10 + l_linenumber)')} % 6 AS INT) AS worker FROM lineitem)"""


def train_sql(
    data: str, mix_cte: str, features: int, classes: int, last: int, kind: str = "step_first", keep: str = "NOT is_test",
    batch: int | None = None, l2: float = 0.0,
) -> str:
    """Unrolled training of ``last`` iterations, ending in CTE ``p<last>``.

    ``kind``: step_first, mix_first, discard, server, single (no mixing of one worker),
    or squares (least squares, one class).  ``batch``: rows of a worker in a slot, or all.
    """
    slots = f"(SELECT greatest(1, count(*) // {6 * (batch or 1)}) FROM ex WHERE {keep})"
    out = [
        data,
        f"""al AS (SELECT row_id, worker, x, {'target AS y' if kind == 'squares' else 'y'},
      {word_sql('slot1', 'row_id') + ' % ' + slots if batch else '0'} AS slot, {slots if batch else '1'} AS n_slots FROM ex WHERE {keep})""",
        mix_cte,
        f"""p0 AS (SELECT CAST(w AS INT) AS worker, CAST(c AS INT) AS cls, CAST(i AS INT) AS idx, 0.0::DOUBLE AS val
      FROM range(6) a(w), range({classes}) b(c), range({features}) d(i))""",
    ]
    for k in range(1, last + 1):
        step = steps.value_at("geometric", k) if kind != "squares" else 0.1
        q, tr, cnt = k - 1, f"tr{k}", f"cnt{k}"
        out.append(f"tr{k} AS (SELECT * FROM al WHERE slot = {q} % n_slots), cnt{k} AS (SELECT worker, count(*) n FROM tr{k} GROUP BY worker)")
        out.append(
            f"lg{k} AS (SELECT e.row_id, e.worker, p.cls, sum(e.x[p.idx + 1] * p.val) z FROM {tr} e JOIN p{q} p ON p.worker = e.worker GROUP BY e.row_id, e.worker, p.cls)"
        )
        if kind == "squares":
            out.append(f"rs{k} AS (SELECT l.row_id, l.worker, l.cls, l.z - e.y AS d FROM lg{k} l JOIN {tr} e ON e.row_id = l.row_id)")
        else:
            out += [
                f"sx{k} AS (SELECT row_id, worker, cls, exp(z - max(z) OVER (PARTITION BY row_id)) ez FROM lg{k})",
                f"rs{k} AS (SELECT s.row_id, s.worker, s.cls, s.ez / sum(s.ez) OVER (PARTITION BY s.row_id) - CASE WHEN s.cls = e.y THEN 1.0 ELSE 0.0 END AS d FROM sx{k} s JOIN {tr} e ON e.row_id = s.row_id)",
            ]
        out.append(
            f"gr{k} AS (SELECT r.worker, r.cls, CAST(i.i AS INT) AS idx, sum(r.d * e.x[i.i + 1]) / any_value(c.n) AS g FROM rs{k} r JOIN {tr} e ON e.row_id = r.row_id JOIN {cnt} c ON c.worker = r.worker, range({features}) i(i) GROUP BY r.worker, r.cls, i.i)"
        )
        mixed = "SELECT m.dst AS worker, h.cls, h.idx, sum(m.w * h.val) AS val FROM {h} h JOIN mix m ON m.src = h.worker AND m.k = {k} GROUP BY m.dst, h.cls, h.idx"
        if kind == "mix_first":
            out.append(f"mx{k} AS ({mixed.format(h=f'p{q}', k=k)})")
            out.append(f"p{k} AS (SELECT p.worker, p.cls, p.idx, p.val - {step} * g.g AS val FROM mx{k} p JOIN gr{k} g USING (worker, cls, idx))")
            continue
        part = ""
        share = "1.0"
        if kind == "discard":
            part = f"JOIN times t ON t.k = {k} AND t.worker = p.worker JOIN schedule s ON s.k = {k}"
            share = "CASE WHEN t.t <= s.cutoff THEN 1.0 ELSE 0.0 END"
        out.append(
            f"hf{k} AS (SELECT p.worker, p.cls, p.idx, p.val - {step} * {share} * (coalesce(g.g, 0) + {l2} * p.val) AS val FROM p{q} p LEFT JOIN gr{k} g ON g.worker = p.worker AND g.cls = p.cls AND g.idx = p.idx {part})"
        )
        out.append(f"p{k} AS ({mixed.format(h=f'hf{k}', k=k)})")
    return ", ".join(out)


_F, _C = len(tasks.SMALL_LETTERS) + 1, 4
_LANG = language_sql(tasks.SMALL_LETTERS)


def _cut(cte: str) -> str:
    return cte.split("WITH RECURSIVE ", 1)[-1].split("WITH ", 1)[-1]


_ADAPT = _cut(O.path_cover()) + ", " + O.METROPOLIS
_FULL = _cut(O.full_wait()) + ", " + O.METROPOLIS
_SERVER = O.times() + ", mix AS (SELECT t.k, t.worker AS dst, CAST(s AS INT) AS src, 1.0::DOUBLE / 6 AS w FROM times t, range(6) r(s))"


def final_params(k: int, features: int = _F) -> str:
    return f"SELECT worker, CAST(cls * {features} + idx AS INT) AS idx, round(val, 6) AS val FROM p{k}"


def lang_sql(mix_cte: str, k: int, kind: str = "step_first", end: str | None = None, more: str = "", **o) -> str:
    return f"WITH RECURSIVE {train_sql(_LANG, mix_cte, _F, _C, k, kind, **o)}{more} {end or final_params(k)}"


# ---- shards, batches, features ------------------------------------------------


@query("m04_iid", f"SELECT doc_id AS row_id, CAST({word_sql('shard1', 'doc_id')} % 6 AS INT) AS worker FROM documents WHERE length(text) > 0")
def _(spark, d):
    return tasks.language(spark, d, "a").select("row_id", "worker")


@query(
    "m04_by_label",
    f"""WITH e AS (SELECT doc_id, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS y, {word_sql('order', 'doc_id')} AS h FROM documents WHERE length(text) > 0)
  SELECT doc_id AS row_id, CAST((row_number() OVER (ORDER BY y, h, doc_id) - 1) * 6 // (SELECT count(*) FROM e) AS INT) AS worker FROM e""",
)
def _(spark, d):
    return tasks.language(spark, d, "a", how="by_label").select("row_id", "worker")


@query("m04_by_source", f"SELECT doc_id AS row_id, CAST({word_sql('key1', 'source')} % 6 AS INT) AS worker FROM documents")
def _(spark, d):
    docs = load(spark, d, "documents").withColumn("row_id", F.col("doc_id"))
    return tasks.shard(docs, 6, "by_key", key="source").select("row_id", "worker")


@query(
    "m04_by_nation",
    f"SELECT o_orderkey AS row_id, CAST({word_sql('key1', 'c_nationkey')} % 25 AS INT) AS worker FROM orders JOIN customer ON c_custkey = o_custkey",
)
def _(spark, d):
    o = load(spark, d, "orders").join(load(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return tasks.shard(o.withColumn("row_id", F.col("o_orderkey")), 25, "by_key", key="c_nationkey").select("row_id", "worker")


@query(
    "m04_sizes",
    f"""WITH e AS (SELECT doc_id AS row_id, {word_sql('quota1', 'doc_id')} / 4294967296.0 AS u FROM documents WHERE length(text) > 0)
  SELECT row_id, CAST(CASE WHEN u < 1/21.0 THEN 0 WHEN u < 1/21.0 + 2/21.0 THEN 1 WHEN u < 1/21.0 + 2/21.0 + 3/21.0 THEN 2
    WHEN u < 1/21.0 + 2/21.0 + 3/21.0 + 4/21.0 THEN 3 WHEN u < 1/21.0 + 2/21.0 + 3/21.0 + 4/21.0 + 5/21.0 THEN 4 ELSE 5 END AS INT) AS worker FROM e""",
)
def _(spark, d):
    return tasks.language(spark, d, "a", how="sizes", sizes=[1, 2, 3, 4, 5, 6]).select("row_id", "worker")


def _quotas(alpha: float, n: int, classes: int, seed: int = 1) -> str:
    cuts = tasks.dirichlet_cuts(alpha, n, classes, seed)
    rows = ", ".join(f"({c}, {i}, {float(v)!r}::DOUBLE)" for c, row in enumerate(cuts) for i, v in enumerate(row[:-1]))
    return f"q(y, i, edge) AS (VALUES {rows})"


@query(
    "m04_dirichlet",
    f"""WITH {_quotas(0.3, 6, 4)}, e AS (SELECT doc_id, list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS y, {word_sql('quota1', 'doc_id')} / 4294967296.0 AS u
    FROM documents WHERE length(text) > 0), w AS (SELECT e.doc_id, any_value(e.y) AS y, count(*) FILTER (q.edge <= e.u) AS worker FROM e JOIN q ON q.y = e.y GROUP BY e.doc_id)
  SELECT CAST(worker AS INT) AS worker, CAST(y AS INT) AS y, count(*) AS n FROM w GROUP BY worker, y""",
)
def _(spark, d):
    ex = tasks.language(spark, d, "a", how="dirichlet", alpha=0.3, n_classes=4)
    return ex.groupBy("worker", "y").agg(F.count(F.lit(1)).alias("n"))


@query("m05_slots", f"SELECT doc_id AS row_id, CAST({word_sql('slot1', 'doc_id')} % 8 AS INT) AS slot FROM documents WHERE length(text) > 0")
def _(spark, d):
    return tasks.assign_slots(tasks.language(spark, d, "a"), 8).select("row_id", "slot")


@query(
    "m05_hash_rank",
    f"""WITH e AS (SELECT doc_id AS row_id, CAST({word_sql('shard1', 'doc_id')} % 6 AS INT) AS worker, {word_sql('batch1|3', 'doc_id')} AS h
  FROM documents WHERE length(text) > 0) SELECT worker, row_id FROM e QUALIFY row_number() OVER (PARTITION BY worker ORDER BY h, row_id) <= 32""",
)
def _(spark, d):
    return tasks.draw_batch(tasks.language(spark, d, "a"), 3, 32).select("worker", "row_id")


@query("f_letters", f"WITH {_LANG} SELECT row_id, y, is_test, round(x[1], 6) AS x1, round(x[3], 6) AS x3, round(x[6], 6) AS x6 FROM ex")
def _(spark, d):
    ex = tasks.language(spark, d, tasks.SMALL_LETTERS)
    return ex.select("row_id", "y", "is_test", *[rounded(F.col("x")[i - 1]).alias(f"x{i}") for i in (1, 3, 6)])


@query(
    "f_global_scale",
    f"""WITH {_LANG}, long AS (SELECT row_id, i, x[i] AS v FROM ex, range(1, {_F + 1}) r(i)),
  st AS (SELECT i, avg(v) m, stddev_pop(v) s FROM long GROUP BY i), g AS (SELECT sqrt(sum(s * s) / count(*)) AS g FROM st)
  SELECT row_id, CAST(i AS INT) AS i, round(CASE WHEN s > 0 THEN (v - m) / g ELSE v END, 5) AS v FROM long JOIN st USING (i), g""",
)
def _(spark, d):
    ex = tasks.standardise(tasks.language(spark, d, tasks.SMALL_LETTERS))
    return ex.select("row_id", F.posexplode("x").alias("i", "v")).select("row_id", (F.col("i") + 1).alias("i"), rounded("v", 5).alias("v"))


def _planted_sql() -> str:
    maps = "SELECT c, list(('0x' || substr(md5('1|' || c || '|' || i), 1, 8))::BIGINT / 4294967296.0 - 0.5 ORDER BY i) AS w FROM range(10) a(c), range(64) b(i) GROUP BY c"
    return f"""WITH maps AS ({maps}), z AS (SELECT vec_id, c, list_dot_product(CAST(embedding AS DOUBLE[]), CAST(w AS DOUBLE[])) AS z FROM embeddings, maps)
  SELECT vec_id AS row_id, CAST(arg_max(c, z) AS INT) AS y FROM z GROUP BY vec_id"""


@query("f_planted_labels", _planted_sql())
def _(spark, d):
    return tasks.planted_examples(load(spark, d, "embeddings")).select("row_id", "y")


@query("f_revenue_tier", f"WITH {TIER_SQL} SELECT y, count(*) AS n, round(avg(x[2]), 6) AS mean_price FROM ex GROUP BY y")
def _(spark, d):
    ex = tasks.revenue_examples(load(spark, d, "lineitem"))
    return ex.groupBy("y").agg(F.count(F.lit(1)).alias("n"), rounded(F.avg(F.col("x")[1])).alias("mean_price"))


@query(
    "f_bigram_hash",
    """WITH t AS (SELECT item_id, lower(text) AS l FROM benchmark WHERE length(text) > 1),
  p AS (SELECT item_id, CAST(('0x' || substr(md5(substr(l, CAST(i AS INT), 2)), 1, 8))::BIGINT % 16 AS INT) AS slot, length(l) - 1 AS n FROM t, range(1, 100000) r(i) WHERE i < length(l))
  SELECT item_id, slot, round(count(*) / any_value(n)::DOUBLE, 6) AS share FROM p GROUP BY item_id, slot""",
)
def _(spark, d):
    b = load(spark, d, "benchmark").filter("length(text) > 1")
    x = tasks.bigram_hash(F.col("text"), 16)
    return b.select("item_id", F.posexplode(x).alias("slot", "share")).filter("share > 0").withColumn("share", rounded("share"))


@query("f_gram_matrix", f"WITH {TIER_SQL} SELECT CAST(i - 1 AS INT) AS i, CAST(j - 1 AS INT) AS j, round(avg(x[i] * x[j]), 6) AS xx FROM ex, range(1, 6) a(i), range(1, 6) b(j) GROUP BY i, j")
def _(spark, d):
    return quality.gram(tasks.revenue_examples(load(spark, d, "lineitem"))).withColumn("xx", rounded("xx"))


def gram_matrix(ex, width: int) -> np.ndarray:
    g = np.zeros((width, width))
    for r in quality.gram(ex).collect():  # width^2 rows
        g[r["i"], r["j"]] = r["xx"]
    return g


@query("f_pca_variance")
def _(spark, d):
    """Explained share of variance by component: Gram by partial sums, eigenvalues on the driver."""
    ex = tasks.standardise(tasks.language(spark, d))
    width = len(tasks.LETTERS)
    long = ex.select("row_id", F.slice("x", 1, width).alias("x"), F.lit(0).alias("y"))
    values = np.linalg.eigvalsh(gram_matrix(long, width))[::-1]
    total = values.sum()
    return spark.createDataFrame([(i, float(round(v / total, 6))) for i, v in enumerate(values)], "component int, share double")


# ---- training, checked against the unrolled statement -------------------------


def small(spark, d):
    return tasks.language(spark, d, tasks.SMALL_LETTERS)


SOFT = Softmax(_F, _C)


def run_small(spark, d, plan, k: int, model=SOFT, **options):
    train = cut(small(spark, d).filter("NOT is_test"))  # features are computed once, not in every iteration
    return relational_train(spark, lambda _: train, plan, model, Config(k_total=k, **options))


def shown(params):
    return params.select("worker", "idx", rounded("val").alias("val"))


@query("m06_gradient", lang_sql(_FULL, 1, end=f"SELECT worker, CAST(cls * {_F} + idx AS INT) AS idx, round(g, 6) AS g FROM gr1"))
def _(spark, d):
    start = mixing.equal_start(spark, N, SOFT.init().tolist())
    return mixing.local_gradient(small(spark, d).filter("NOT is_test"), start, SOFT).select("worker", "idx", rounded("g").alias("g"))


@query("m06_gradient_arrow", ORACLE_SQL["m06_gradient"])
def _(spark, d):
    params = {w: SOFT.init() for w in range(N)}
    return mixing.arrow_gradient(small(spark, d).filter("NOT is_test"), params, SOFT).select("worker", "idx", rounded("g").alias("g"))


@query("m07_half_step", lang_sql(_FULL, 1, end=f"SELECT worker, CAST(cls * {_F} + idx AS INT) AS idx, round(val, 6) AS val FROM hf1"))
def _(spark, d):
    start = mixing.equal_start(spark, N, SOFT.init().tolist())
    grad = mixing.local_gradient(small(spark, d).filter("NOT is_test"), start, SOFT)
    return shown(mixing.half_step(start, grad, steps.value_at("geometric", 1)))


@query("m08_mix", lang_sql(_ADAPT, 1))
def _(spark, d):
    start = mixing.equal_start(spark, N, SOFT.init().tolist())
    half = mixing.half_step(start, mixing.local_gradient(small(spark, d).filter("NOT is_test"), start, SOFT), steps.value_at("geometric", 1))
    p = adaptive(spark, d)
    return shown(mixing.mix(half, weights.metropolis(p.active.filter("k = 1"), p.times.filter("k = 1"))))


_RUNS = {
    "w01_full_k1": (1, _FULL, "step_first", full, {}),
    "w01_full_k3": (3, _FULL, "step_first", full, {}),
    "w01_adaptive_k3": (3, _ADAPT, "step_first", adaptive, {}),
    "w01_adaptive_late_discard_k3": (3, _ADAPT, "discard", adaptive, {"late": "discard"}),
    "w01_mix_first_k3": (3, _FULL, "mix_first", full, {"order": "mix_first"}),
    "w01_server_sync_k3": (
        3, _SERVER, "server", lambda spark, d, last: waiting.ServerSync().plan(early(spark, d, last), six(spark)), {"weights": "uniform"},
    ),
}
for _name, (_k, _mix, _kind, _plan, _opt) in _RUNS.items():
    query(_name, lang_sql(_mix, _k, _kind))(
        lambda spark, d, k=_k, plan=_plan, o=_opt: shown(run_small(spark, d, plan(spark, d, k), k, **o))
    )


@query("w04_adaptive_k2", f"WITH RECURSIVE {train_sql(TIER_SQL, _ADAPT, 5, 3, 2)} {final_params(2, 5)}")
def _(spark, d):
    ex = cut(tasks.shard(tasks.revenue_examples(load(spark, d, "lineitem")), N).filter("NOT is_test"))
    return shown(relational_train(spark, lambda _: ex, adaptive(spark, d, 2), Softmax(5, 3), Config(k_total=2)))


def squares(spark, d):
    return tasks.shard(tasks.revenue_examples(load(spark, d, "lineitem"), "regression"), N)


@query("w15_least_squares_k3", f"WITH RECURSIVE {train_sql(TIER_SQL, _ADAPT, 5, 1, 3, 'squares')} {final_params(3, 5)}")
def _(spark, d):
    ex = cut(squares(spark, d).filter("NOT is_test"))
    config = Config(k_total=3, step="constant", step_options={"c": 0.1})
    return shown(relational_train(spark, lambda _: ex, adaptive(spark, d, 3), LeastSquares(5), config))


@query("w01_slot_batches_k3", lang_sql(_ADAPT, 3, batch=32))
def _(spark, d):
    """Three iterations on mini-batches of 32 rows a worker, each read from its own directory."""
    config = Config(k_total=3, batch=32)
    slots = Slots(small(spark, d).filter("NOT is_test"), config)
    return shown(relational_train(spark, slots.frame, adaptive(spark, d, 3), SOFT, config))


@query("w01_slot_batches_arrow_k3", lang_sql(_ADAPT, 3, batch=32))
def _(spark, d):
    """The same in the vectorised loop."""
    return shown(trained(spark, small(spark, d), adaptive(spark, d, 3), SOFT, Config(k_total=3, eval_every=3, batch=32))[0])


@query("m03_regulariser_k3", lang_sql(_FULL, 3, l2=0.1))
def _(spark, d):
    """Training under a squared penalty on the parameters."""
    return shown(run_small(spark, d, full(spark, d, 3), 3, Softmax(_F, _C, 0.1)))


@query("m03_regulariser_arrow_k3", lang_sql(_FULL, 3, l2=0.1))
def _(spark, d):
    config = Config(k_total=3, eval_every=3, batch=None)
    return shown(trained(spark, small(spark, d), full(spark, d, 3), Softmax(_F, _C, 0.1), config)[0])


@query("m06_gradient_by_place", lang_sql(_FULL, 1, end=f"SELECT worker, CAST(cls * {_F} + idx AS INT) AS idx, round(g, 6) AS g FROM gr1"))
def _(spark, d):
    """The gradient with parameters joined by place: for states too large to broadcast."""
    start = mixing.equal_start(spark, N, SOFT.init().tolist())
    return mixing.long_gradient(small(spark, d).filter("NOT is_test"), start, SOFT).select("worker", "idx", rounded("g").alias("g"))


@query("m15_tail_limit", lang_sql(_FULL, 1, end=f"SELECT CAST(w AS INT) AS worker, CAST(cls * {_F} + idx AS INT) AS idx, round(avg(val), 6) AS val FROM p1, range(6) a(w) GROUP BY w, cls, idx"))
def _(spark, d):
    """Mixing alone takes every worker to the mean vector."""
    p = full(spark, d)
    params = run_small(spark, d, p, 1)
    m = weights.matrices(weights.metropolis(p.active.filter("k <= 2"), p.times.filter("k <= 2")), N)[1]
    return shown(tail.consensus_phase(spark, params, [m] * 400)[0])


@query("m16_mean_iterate", lang_sql(_ADAPT, 3, end=f"SELECT CAST(cls * {_F} + idx AS INT) AS idx, round(avg(val), 6) AS val FROM p3 GROUP BY cls, idx"))
def _(spark, d):
    return mixing.mean_model(run_small(spark, d, adaptive(spark, d, 3), 3)).select("idx", rounded("val").alias("val"))


@query("m19_output_worker0", lang_sql(_FULL, 1, end=f"SELECT CAST(cls * {_F} + idx AS INT) AS idx, round(val, 6) AS val FROM p1 WHERE worker = 0"))
def _(spark, d):
    return tail.output_model(run_small(spark, d, full(spark, d, 1), 1), "worker", 0).select("idx", rounded("val").alias("val"))


_EACH = """, ez AS (SELECT e.row_id, e.y, e.is_test, p.worker AS w, p.cls, sum(e.x[p.idx + 1] * p.val) z FROM ex e CROSS JOIN p3 p GROUP BY ALL),
  es AS (SELECT row_id, w, any_value(is_test) is_test, any_value(y) y, max(z) + ln(sum(exp(z - mx))) - sum(CASE WHEN cls = y THEN z ELSE 0 END) AS l,
    arg_max(cls, (z, -cls)) AS predicted FROM (SELECT *, max(z) OVER (PARTITION BY row_id, w) mx FROM ez) GROUP BY row_id, w)"""


@query("m19_output_best", lang_sql(_ADAPT, 3, more=_EACH, end=f"""SELECT p.worker, CAST(cls * {_F} + idx AS INT) AS idx, round(val, 6) AS val FROM p3 p
  WHERE p.worker = (SELECT arg_min(w, (l, w)) FROM (SELECT w, round(avg(l), 9) AS l FROM es WHERE NOT is_test GROUP BY w))"""))
def _(spark, d):
    """The parameters of the worker whose own model has the least training loss."""
    p = cut(run_small(spark, d, adaptive(spark, d, 3), 3))
    return shown(tail.best_worker(small(spark, d).filter("NOT is_test"), p, SOFT))


@query("a02_worker_errors", lang_sql(_ADAPT, 3, more=_EACH, end="""SELECT w AS worker, round(avg(CASE WHEN predicted <> y THEN 1.0 ELSE 0.0 END), 6)::DOUBLE AS error,
  round(max(avg(CASE WHEN predicted <> y THEN 1.0 ELSE 0.0 END)) OVER (), 6)::DOUBLE AS worst FROM es WHERE is_test GROUP BY w"""))
def _(spark, d):
    """Test error of each worker's own model, beside the worst."""
    e = cut(quality.worker_errors(small(spark, d).filter("is_test"), run_small(spark, d, adaptive(spark, d, 3), 3), SOFT))
    return e.join(F.broadcast(e.agg(F.max("error").alias("worst"))), F.lit(True)).select("worker", rounded("error").alias("error"), rounded("worst").alias("worst"))


@query("md4_quadratic_k3", f"WITH RECURSIVE {train_sql(TIER_SQL.replace('AS x,', 'AS xs, [1.0]::DOUBLE[] AS x,'), _ADAPT, 1, 1, 3, 'squares')} {final_params(3, 1)}")
def _(spark, d):
    """The scalar quadratic: workers seek the mean target of their shards."""
    ex = squares(spark, d).withColumn("x", F.array(F.lit(1.0)))
    config = Config(k_total=3, eval_every=3, step="constant", step_options={"c": 0.1}, batch=None)
    return shown(trained(spark, ex, adaptive(spark, d, 3), Quadratic(), config)[0])


@query("r1_constant", f"WITH {O.times()} SELECT DISTINCT k, round(0.05::DOUBLE, 9) AS step FROM times")
def _(spark, d):
    """The step of each iteration of the trace; every iteration has one time of worker 0."""
    return trace(spark, d).filter("worker = 0").select("k", F.round(steps.constant(0.05)(F.col("k")), 9).alias("step"))


_STEPS = {
    "r2_geometric": (steps.geometric(), "0.2 * pow(0.95, k)"),
    "r3_horizon": (steps.horizon(6, 200), "sqrt(6 / 200.0)"),
}
for _name, (_policy, _sql) in _STEPS.items():
    query(_name, f"SELECT CAST(k AS INT) AS k, round({_sql}, 9) AS step FROM range(1, 201) r(k)")(
        lambda spark, d, p=_policy: spark.range(1, 201).select(F.col("id").cast("int").alias("k"), F.round(p(F.col("id")), 9).alias("step"))
    )


@query("r4_per_worker", "SELECT CAST(w AS INT) AS worker, round(0.1 * (w + 1), 6)::DOUBLE AS step FROM range(6) r(w)")
def _(spark, d):
    policy = steps.per_worker({i: 0.1 * (i + 1) for i in range(6)})
    return spark.range(6).select(F.col("id").cast("int").alias("worker"), rounded(policy(F.lit(1), F.col("id").cast("int"))).alias("step"))


@query("r5_batch_proportional", f"{O.path_cover()} SELECT t.k, round(0.2 * sum(CAST(t.t <= s.cutoff AS INT)) / 6.0, 6) AS step FROM times t JOIN schedule s USING (k) GROUP BY t.k")
def _(spark, d):
    p = adaptive(spark, d)
    ready = waiting.on_time(p.times, p.schedule).groupBy("k").agg(F.sum(F.col("on_time").cast("double")).alias("a"))
    return ready.select("k", rounded(steps.batch_proportional(0.2)(F.lit(1), F.col("a"), F.lit(6.0))).alias("step"))


def both_plans(spark, d, last: int, cover=None, edges=None, times=None):
    """Full wait and path cover over the first ``last`` iterations, which a run of that length reads."""
    t = cut((trace(spark, d) if times is None else times).filter(F.col("k") <= last))
    e = six(spark) if edges is None else edges
    return {"full": waiting.FullWait().plan(t, e), "adaptive": waiting.PathCover(cover or graphs.SIX_COVER, warmup_full=True).plan(t, e)}


# ---- accuracy after one full-wait iteration ------------------------------------

_MEAN = f""", mm AS (SELECT cls, idx, avg(val) AS val FROM p1 GROUP BY cls, idx),
  zz AS (SELECT e.row_id, e.worker, e.y, e.is_test, m.cls, sum(e.x[m.idx + 1] * m.val) z FROM ex e CROSS JOIN mm m GROUP BY ALL),
  ls AS (SELECT row_id, any_value(worker) worker, any_value(is_test) is_test, any_value(y) y,
    max(z) + ln(sum(exp(z - mx))) - sum(CASE WHEN cls = y THEN z ELSE 0 END) AS l, arg_max(cls, (z, -cls)) AS predicted
    FROM (SELECT *, max(z) OVER (PARTITION BY row_id) mx FROM zz) GROUP BY row_id)"""


def _one(spark, d):
    return run_small(spark, d, full(spark, d, 1), 1)


@query("a01_loss", lang_sql(_FULL, 1, more=_MEAN, end="SELECT round(avg(l), 6) AS loss FROM (SELECT avg(l) AS l FROM ls WHERE NOT is_test GROUP BY worker)"))
def _(spark, d):
    return quality.worker_mean_loss(small(spark, d).filter("NOT is_test"), _one(spark, d), SOFT).select(rounded("loss").alias("loss"))


@query("a01_pooled_loss", lang_sql(_FULL, 1, more=_MEAN, end="SELECT round(avg(l), 6) AS loss, round(sum(l), 4) AS total FROM ls WHERE NOT is_test"))
def _(spark, d):
    p = quality.pooled_loss(small(spark, d).filter("NOT is_test"), _one(spark, d), SOFT)
    return p.select(rounded("loss").alias("loss"), rounded("total", 4).alias("total"))


@query("a02_test_error", lang_sql(_FULL, 1, more=_MEAN, end="SELECT round(avg(CASE WHEN predicted <> y THEN 1.0 ELSE 0.0 END), 6)::DOUBLE AS error, count(*) AS n FROM ls WHERE is_test"))
def _(spark, d):
    e = quality.test_error(small(spark, d).filter("is_test"), _one(spark, d), SOFT)
    return e.select(rounded("error").alias("error"), "n")


@query("a30_confusion", lang_sql(_FULL, 1, more=_MEAN, end="SELECT y, predicted, count(*) AS n FROM ls WHERE is_test GROUP BY y, predicted"))
def _(spark, d):
    return quality.confusion(small(spark, d).filter("is_test"), _one(spark, d), SOFT)


@query("a09_disagreement", lang_sql(_FULL, 1, end="""SELECT round(max(d), 9) AS largest, round(avg(d), 9) AS mean FROM (SELECT p.worker, sum(pow(p.val - m.v, 2)) d
  FROM p1 p JOIN (SELECT cls, idx, avg(val) v FROM p1 GROUP BY cls, idx) m ON m.cls = p.cls AND m.idx = p.idx GROUP BY p.worker)"""))
def _(spark, d):
    return mixing.disagreement(_one(spark, d)).select(rounded("largest", 9).alias("largest"), rounded("mean", 9).alias("mean"))


@query("a10_gradient_norm", lang_sql(_FULL, 1, end="SELECT worker, round(sum(g * g), 6) AS norm2 FROM gr1 GROUP BY worker"))
def _(spark, d):
    start = mixing.equal_start(spark, N, SOFT.init().tolist())
    return quality.gradient_norm(small(spark, d).filter("NOT is_test"), start, SOFT).select("worker", rounded("norm2").alias("norm2"))


@query("a19_gradient_variance", lang_sql(_FULL, 1, end=f"""SELECT worker, round(sum(v), 6) AS variance FROM (SELECT r.worker, r.cls, i.i, var_pop(r.d * e.x[i.i + 1]) v
  FROM rs1 r JOIN tr1 e ON e.row_id = r.row_id, range({_F}) i(i) GROUP BY r.worker, r.cls, i.i) GROUP BY worker"""))
def _(spark, d):
    start = mixing.equal_start(spark, N, SOFT.init().tolist())
    return quality.gradient_variance(small(spark, d).filter("NOT is_test"), start, SOFT).select("worker", rounded("variance").alias("variance"))


# ---- theory --------------------------------------------------------------------


def scalar_start(spark, d):
    """The scalar quadratic on the events' values in hundreds: squared distance from 0 to its optimum, the mean, and the
    variance of its gradients; its smoothness is 1.  One row."""
    y = F.col("value") / 100
    return load(spark, d, "events").agg(rounded(F.pow(F.avg(y), 2)).alias("distance2"), rounded(F.var_pop(y)).alias("variance"))


@query(
    "a16_bound",
    f"""WITH {O.times()}, z AS (SELECT round(pow(avg(value / 100), 2), 6) AS distance2, round(var_pop(value / 100), 6) AS v FROM events)
  SELECT k, round(distance2 / (0.1::DOUBLE * k) + pow(0.05::DOUBLE, 2) / 12 * v, 9) AS bound,
    round(distance2 / (0.1::DOUBLE * k) + 0.05::DOUBLE / 12 * v, 9) AS bound_power1 FROM times, z WHERE worker = 0""",
)
def _(spark, d):
    """The loss-gap bound of the scalar quadratic at each iteration of the trace."""
    b = lambda p: F.round(theory.loss_gap_bound(F.col("k"), F.col("distance2"), 0.05, 1.0, N, F.col("variance"), p), 9)
    k = trace(spark, d).filter("worker = 0").select("k")
    return k.join(F.broadcast(scalar_start(spark, d))).select("k", b(2).alias("bound"), b(1).alias("bound_power1"))


@query(
    "a17_required",
    """WITH c AS (SELECT user_id % 25 AS worker, sum(value) AS s, count(*) AS m FROM events WHERE value IS NOT NULL AND user_id IS NOT NULL GROUP BY user_id % 25),
  w AS (SELECT row_number() OVER o AS n, round(sum(s) OVER o / sum(m) OVER o / 100, 6) AS mean FROM c WINDOW o AS (ORDER BY worker)),
  t AS (SELECT n, nullif(0.125::DOUBLE * (0.5::DOUBLE * mean * mean), 0) AS tol FROM w)
  SELECT CAST(n AS INT) AS n, CAST(ceil(1 / (tol * tol * n)) AS BIGINT) AS iterations FROM t""",
)
def _(spark, d):
    """Iterations until the scalar quadratic's gap is an eighth of its start's, for the first n of 25 workers.

    Its data are the values, in hundreds, of the workers' events.
    """
    e = load(spark, d, "events").filter("value IS NOT NULL AND user_id IS NOT NULL")
    per = e.groupBy((F.col("user_id") % 25).alias("worker")).agg(F.sum("value").alias("s"), F.count(F.lit(1)).alias("m"))
    upto = W.orderBy("worker")  # a row per worker
    w = per.select(F.row_number().over(upto).alias("n"), rounded(F.sum("s").over(upto) / F.sum("m").over(upto) / 100).alias("mean"))
    tol = F.nullif(0.125 * (0.5 * F.col("mean") * F.col("mean")), F.lit(0.0))
    return w.select("n", theory.iterations_required(tol, F.col("n")).alias("iterations"))


@query("a15_gradient_bound")
def _(spark, d):
    """The gradient bound of the scalar quadratic on the traces of two and three workers in a row, after all iterations.

    An epoch visits the cover, so it is as long as that; the smallest weight is measured.
    """
    start, rows = scalar_start(spark, d).first(), []
    for n in (2, 3):
        row = graphs.graph("path", n)
        p = waiting.PathCover(row).plan(cut(trace(spark, d, n)), graphs.edges(spark, row))
        beta = weights.smallest_weight(weights.metropolis(p.active, p.times).filter("w > 1e-12")).first()["beta"]
        if beta is None:  # no iteration has all workers
            continue
        b, last = len(row), p.times.agg(F.max("k")).first()[0]
        bound = theory.gradient_bound(last, start["distance2"] / 2, 0.05, 1.0, n, b, beta, start["variance"])
        rows.append((n, b, beta, float(theory.min_iterations_for_bound(n, b, beta, 0.01)), float(bound)))
    return spark.createDataFrame(rows, "n int, b int, beta double, from_iteration double, bound double")


@query("a18_smoothness")
def _(spark, d):
    ex = tasks.language(spark, d)
    g = gram_matrix(ex.select("x", "y"), len(tasks.LETTERS) + 1)
    return spark.createDataFrame([(theory.smoothness(g), theory.smoothness(g, "squares"))], "softmax double, squares double")


@query("a11_loss_gap")
def _(spark, d):
    """Least squares: gap of the mean model to the closed-form optimum, with the printed bound."""
    ex = squares(spark, d)
    train = ex.filter("NOT is_test")
    g = gram_matrix(train, 5)
    xy = np.zeros(5)
    for r in quality.moment(train).collect():
        xy[r["i"]] = r["xy"]
    best = least_squares_optimum(g, xy)
    c = float(train.agg(F.avg(F.col("y") * F.col("y"))).first()[0])
    least = 0.5 * (c - 2 * best @ xy + best @ g @ best)
    config = Config(k_total=60, eval_every=10, step="constant", step_options={"c": 0.1}, batch=None)
    h = compare(spark, ex, both_plans(spark, d, 60), LeastSquares(5), config)
    bound = theory.loss_gap_bound(F.col("k"), float(best @ best), 0.1, theory.smoothness(g, "squares"), N, 0.0)
    return h.select("run", "k", (F.col("loss") - float(least)).alias("gap"), bound.alias("bound"))


@query("m18_unrolled")
def _(spark, d):
    """Largest difference between a run's parameters and its closed expansion, on the run's own gradients."""
    k, grads, start = 12, [], []

    def watch(_, runs, g):
        start.append(runs[0].w.copy())
        grads.append(g[0].copy())

    plan = adaptive(spark, d, k)
    config = Config(k_total=k, eval_every=k, batch=32)
    runs, _ = train_runs(spark, small(spark, d), {"adaptive": plan}, SOFT, config, watch)
    eta, mats = [float(config.step_at(i)[0]) for i in range(1, k + 1)], [runs[0].mats[i] for i in range(1, k + 1)]
    diff = float(np.abs(tail.unrolled(start[0], grads, eta, mats) - runs[0].w).max())
    mean = float(np.abs(tail.mean_iterate(start[0], grads, eta) - runs[0].w.mean(axis=0)).max())
    return spark.createDataFrame([(k, diff < 1e-12, mean < 1e-12)], "k int, expansion_equals boolean, mean_equals boolean")


@query("m21_exact_wait")
def _(spark, d):
    """Least total wait that keeps every three successive unions connected, by enumeration over four
    iterations of the four-worker graph, beside the path cover and full wait."""
    from consensus_spark.operators.schedule import exact_min_wait, path_cover_schedule, times_by_iteration

    t = cut(trace(spark, d, 4).filter("k <= 24"))
    cover = {r["k"]: r["cutoff"] for r in path_cover_schedule(t, graphs.FOUR_COVER).select("k", "cutoff").collect()}
    at = {r["k"]: r["at"] for r in times_by_iteration(t).collect()}
    rows = []
    for first in range(1, 24, 3):
        ks = [k for k in range(first, first + 3) if k in at]
        exact = exact_min_wait([at[k] for k in ks], graphs.FOUR, 4, 3)
        rows.append((first, float(exact), float(sum(cover[k] for k in ks)), float(sum(max(at[k]) for k in ks))))
    return spark.createDataFrame(rows, "first int, exact double, path_cover double, full double")


@query("t9_measured_times")
def _(spark, d):
    """Compute times measured: seconds of each worker's gradient kernel on each of eight slots."""
    import time

    from consensus_spark.sources.times import measured

    ex = tasks.assign_slots(tasks.language(spark, d), 8).filter("NOT is_test").select((F.col("slot") + 1).alias("k"), "worker", "x", "y")
    model = Softmax(len(tasks.LETTERS) + 1, 4)
    w = model.init()

    def timed(batches):
        import pyarrow as pa

        for b in batches:
            k, worker = np.asarray(b.column("k")), np.asarray(b.column("worker"))
            x, y = np.asarray(b.column("x").flatten()).reshape(b.num_rows, -1), np.asarray(b.column("y"))
            pairs = np.unique(np.stack([k, worker]), axis=1).T if b.num_rows else []
            for i, j in pairs:
                at = (k == i) & (worker == j)
                begun = time.perf_counter()
                model.grad_sum(w, x[at], y[at])
                yield pa.record_batch([pa.array([i], pa.int32()), pa.array([j], pa.int32()), pa.array([time.perf_counter() - begun])], ["k", "worker", "seconds"])

    return measured(ex.mapInArrow(timed, "k int, worker int, seconds double"))


# ---- baselines discussed, as simulators ----------------------------------------


def arrivals(t):
    """Every update of every worker by order of arrival: running totals over whole chunks of
    iterations first, then inside chunks."""
    from pyspark.sql import Window as W

    t = t.withColumn("_c", F.floor(F.col("k") / 4096))
    upto = W.partitionBy("worker").orderBy("_c").rowsBetween(W.unboundedPreceding, -1)
    starts = t.groupBy("worker", "_c").agg(F.sum("t").alias("_s")).select(
        "worker", "_c", F.coalesce(F.sum("_s").over(upto), F.lit(0.0)).alias("_start")
    )
    inside = W.partitionBy("worker", "_c").orderBy("k").rowsBetween(W.unboundedPreceding, 0)
    done = t.withColumn("_l", F.sum("t").over(inside)).join(starts, ["worker", "_c"]).select(
        "worker", "k", F.round(F.col("_start") + F.col("_l"), 6).alias("arrival")
    )
    return rank_within(done, [], F.floor(F.col("arrival") / 5000.0), ["arrival", "worker"], "version")


@query(
    "b09_server_async",
    f"""WITH {O.times()}, a AS (SELECT worker, k, round(sum(t) OVER (PARTITION BY worker ORDER BY k), 6) AS arrival FROM times),
  v AS (SELECT *, row_number() OVER (ORDER BY arrival, worker) AS version FROM a)
  SELECT v.worker, v.k, round(v.arrival, 4) AS arrival, v.version, v.version - coalesce(b.version, 0) - 1 AS staleness
  FROM v LEFT JOIN v b ON b.worker = v.worker AND b.k = v.k - 1""",
)
def _(spark, d):
    """A server that applies each update on arrival: staleness of every update (event order)."""
    done = arrivals(trace(spark, d))
    before = done.select("worker", (F.col("k") + 1).alias("k"), F.col("version").alias("_read"))
    read = F.coalesce("_read", F.lit(0))
    return done.join(before, ["worker", "k"], "left").select(
        "worker", "k", rounded("arrival", 4).alias("arrival"), "version", (F.col("version") - read - 1).alias("staleness")
    )


@query("b10_stale_sync")
def _(spark, d):
    """Finish times when nobody may run more than a bound ahead of the slowest."""
    # a fold over all iterations; it holds the last few finish times of each bound
    steps = trace(spark, d).groupBy("k").agg(F.collect_list(F.struct("worker", "t")).alias("ts")).orderBy("k")
    past = {bound: [[0.0] * N] for bound in (0, 1, 4)}
    for r in steps.toLocalIterator():
        t = dict(r["ts"])
        for bound, finish in past.items():
            gate = max(finish[max(0, len(finish) - 1 - bound)])
            finish.append([max(finish[-1][w], gate) + t[w] for w in range(N)])
            del finish[: -bound - 1]
    out = [(bound, float(max(finish[-1]))) for bound, finish in past.items()]
    return spark.createDataFrame(out, "bound int, finished double")
