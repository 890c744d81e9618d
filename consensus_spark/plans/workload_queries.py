"""The experiment workloads: curves, sweeps and transfers on the given tables.

Runs take mini-batches of 1,024 rows a worker and last until the decaying step has
frozen them; histories are rows only, their behaviour is checked by pytest.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from consensus_spark.operators import mixing, quality, tail, waiting, weights
from consensus_spark.operators.models import Mlp, Softmax
from consensus_spark.operators.weights import rounded
from consensus_spark.plans import tasks
from consensus_spark.plans.durable import cut
from consensus_spark.plans.schedule_queries import N, adaptive, six, trace
from consensus_spark.plans.trainer import Config, compare, train_runs, trained
from consensus_spark.plans.training_queries import both_plans
from consensus_spark.sources import graphs
from consensus_spark.sources.tables import load
from consensus_spark.sources.times import law

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
LONG = 120
LETTERS = len(tasks.LETTERS) + 1


def query(name: str):
    def add(f):
        QUERIES[name] = f
        return f

    return add


def curve(spark, d, ex, model, k: int = LONG, plans=None, n: int = N, **o):
    o.setdefault("eval_every", max(1, k // 12))
    return compare(spark, ex, plans or both_plans(spark, d, k), model, Config(k_total=k, n=n, **o))


def planted(spark, d, **o):
    return tasks.shard(tasks.planted_examples(load(spark, d, "embeddings"), **o), N)


def stacked(parts):
    """Histories of several settings under one another; each named in ``run``."""
    out = None
    for name, h in parts:
        h = h.withColumn("run", F.concat(F.col("run"), F.lit(f"_{name}")))
        out = h if out is None else out.unionByName(h)
    return out


@query("w01_curve")
def _(spark, d):
    """Language task: both rules on the same data and times, until the step has frozen."""
    return curve(spark, d, tasks.language(spark, d), Softmax(LETTERS, 4))


@query("w02_curve")
def _(spark, d):
    """Planted ten classes on all 64 features."""
    return curve(spark, d, planted(spark, d), Softmax(65, 10))


@query("w03_noise_curve")
def _(spark, d):
    return curve(spark, d, planted(spark, d, noise=True), Softmax(65, 10), 40)


@query("w04_curve")
def _(spark, d):
    ex = tasks.shard(tasks.revenue_examples(load(spark, d, "lineitem")), N)
    return curve(spark, d, ex, Softmax(5, 3))


@query("w05_mlp")
def _(spark, d):
    """The net of two hidden layers on both tasks."""
    o = {"step": "constant", "step_options": {"c": 0.2}}
    return stacked(
        [
            ("language", curve(spark, d, tasks.language(spark, d), Mlp(LETTERS, 4), 60, **o)),
            ("planted", curve(spark, d, planted(spark, d), Mlp(65, 10), 60, **o)),
        ]
    )


def bigram_task(spark, d, dims: int = 256):
    """Hashed letter pairs of whole documents with the language task's labels and shards."""
    docs = load(spark, d, "documents").withColumn("row_id", F.col("doc_id"))
    labels = tasks.language(spark, d, "a").select("row_id", "y", "is_test", "worker")
    return cut(tasks.bigram_examples(docs.select("row_id", "text"), dims).dropDuplicates(["row_id"]).join(labels, "row_id"))


@query("w06_pca_curve")
def _(spark, d):
    """Sixteen leading components in front of both tasks: bigrams 256 to 16, vectors 64 to 16."""
    parts = []
    for name, ex, width, classes in (("bigrams", bigram_task(spark, d), 256, 4), ("vectors", planted(spark, d), 64, 10)):
        pca = tasks.Pca.fit(ex.filter("NOT is_test"), width, 16)
        parts.append((name, curve(spark, d, pca.apply(ex), Softmax(17, classes))))
    return stacked(parts)


@query("w06_explained_variance")
def _(spark, d):
    """Share of variance of each leading component, by task."""
    rows = []
    for name, ex, width in (("bigrams", bigram_task(spark, d), 256), ("vectors", planted(spark, d), 64)):
        share = tasks.Pca.fit(ex.filter("NOT is_test"), width, 16).share
        rows += [(name, i, float(v)) for i, v in enumerate(share)]
    return spark.createDataFrame(rows, "task string, component int, share double")


@query("w07_batch_sweep")
def _(spark, d):
    """Batches of 32 to 1,024 rows a worker and whole shards, with the gradient variance of a batch at the start."""
    ex = cut(tasks.shard(tasks.revenue_examples(load(spark, d, "lineitem")), N))
    model, plan = Softmax(5, 3), both_plans(spark, d, 60)["adaptive"]
    start = mixing.equal_start(spark, N, model.init().tolist())
    train = ex.filter("NOT is_test")
    row = quality.gradient_variance(train, start, model).agg(F.avg("variance")).first()[0]
    shard = train.count() / N
    out = None
    for m in (32, 128, 512, 1024, None):
        h = compare(spark, ex, {f"batch_{m or 'full'}": plan}, model, Config(k_total=60, eval_every=10, batch=m))
        # a batch drawn without replacement from its shard
        h = h.withColumn("batch_variance", F.lit(0.0 if m is None else row / m * max(0.0, 1 - m / shard)))
        out = h if out is None else out.unionByName(h)
    return out


@query("w07_iterations_to")
def _(spark, d):
    return quality.iterations_to(QUERIES["w07_batch_sweep"](spark, d), "loss", 0.9)


@query("w10_noniid")
def _(spark, d):
    """Equal, by-label, by-source and Dirichlet shards: history, and gradient variance at the start."""
    docs = load(spark, d, "documents")
    by_source = tasks.language_examples(docs).join(
        tasks.shard(docs.withColumn("row_id", F.col("doc_id")), N, "by_key", key="source").select("row_id", "worker").dropDuplicates(["row_id"]), "row_id"
    )
    cases = {
        "iid": tasks.language(spark, d), "by_label": tasks.language(spark, d, how="by_label"), "source": by_source,
        "dirichlet": tasks.language(spark, d, how="dirichlet", alpha=0.3, n_classes=4),
    }
    model, parts = Softmax(LETTERS, 4), []
    start = mixing.equal_start(spark, N, model.init().tolist())
    for how, ex in cases.items():
        ex = cut(ex)
        v = quality.gradient_variance(ex.filter("NOT is_test"), start, model).agg(F.avg("variance")).first()[0]
        parts.append((how, curve(spark, d, ex, model, 60).withColumn("gradient_variance", F.lit(float(v)))))
    return stacked(parts)


@query("w13_time_to_accuracy")
def _(spark, d):
    """First iteration and clock at which training loss and test error reach their targets."""
    h = curve(spark, d, tasks.language(spark, d), Softmax(LETTERS, 4), eval_every=2)
    loss = quality.iterations_to(h, "loss", 0.3).withColumnsRenamed({"k": "k_loss", "clock": "clock_loss"})
    error = quality.iterations_to(h, "test_error", 0.01).withColumnsRenamed({"k": "k_error", "clock": "clock_error"})
    return loss.join(error, "run")


@query("w14_steps")
def _(spark, d):
    """The five step policies under the path cover, each for a whole run of 100 iterations."""
    k, model, out = 100, Softmax(LETTERS, 4), None
    ex, plan = cut(tasks.language(spark, d)), both_plans(spark, d, 100)["adaptive"]
    for name, kind, o in (
        ("constant", "constant", {"c": 0.1}), ("geometric", "geometric", {}), ("horizon", "horizon", {"n": N, "last": k}),
        ("per_worker", "per_worker", {"steps": [0.05 * (i + 1) for i in range(N)]}), ("batch_proportional", "batch_proportional", {"c": 0.2}),
    ):
        h = compare(spark, ex, {name: plan}, model, Config(k_total=k, eval_every=20, step=kind, step_options=o))
        out = h if out is None else out.unionByName(h)
    return out


TOLS = [1e-2, 1e-4, 1e-6, 1e-8, 1e-10]
TRAINED = 30


def tail_of(spark, d):
    """Parameters of a non-iid run, and the matrices of all iterations after it."""
    p = adaptive(spark, d)
    near, ex = cut(p.times.filter(F.col("k") <= TRAINED)), tasks.language(spark, d, how="by_label")
    plan = waiting.PathCover(graphs.SIX_COVER).plan(near, six(spark))
    _, w = trained(spark, ex, plan, Softmax(LETTERS, 4), Config(k_total=TRAINED, eval_every=TRAINED, step="constant", step_options={"c": 0.2}))
    after = F.col("k") > TRAINED
    return w, (m for _, m in weights.in_order(weights.metropolis(p.active.filter(after), p.times.filter(after)), N))


@query("w16_tail")
def _(spark, d):
    """Spread of trained parameters over all iterations after training, which only mix, and drift of their mean."""
    rows, _ = tail.iterations_to_agree(*tail_of(spark, d), TOLS, whole=True)
    return spark.createDataFrame([(TRAINED + i, s, m) for i, s, m in rows], "k int, disagreement double, mean_drift double")


@query("a28_tail_length")
def _(spark, d):
    """Mixing-only iterations until the spread is at a tolerance, from trained parameters."""
    _, first = tail.iterations_to_agree(*tail_of(spark, d), TOLS)
    return spark.createDataFrame([(t, first.get(t)) for t in TOLS], "tolerance double, iterations int")


@query("w17_training_ablations")
def _(spark, d):
    """Waiting policies, orders, warm-up and late gradients in training: disagreement, iterations and clock to a loss."""
    k, model = 60, Softmax(LETTERS, 4)
    t, e, ex = cut(trace(spark, d).filter(F.col("k") <= k)), six(spark), cut(tasks.language(spark, d, how="by_label"))
    cover = lambda **o: waiting.PathCover(graphs.SIX_COVER, **o).plan(t, e)
    plans = {
        "full": waiting.FullWait().plan(t, e), "cover": cover(), "cover_warmup": cover(warmup_full=True), "cover_ties_all": cover(ties="all"),
        "fastest1": waiting.FastestCount(1).plan(t, e), "fastest2": waiting.FastestCount(2).plan(t, e),
        "fastest2_union": waiting.FastestCount(2, "union").plan(t, e), "fixed_40": waiting.FixedCutoff(40.0).plan(t, e),
        "median": waiting.QuantileCutoff(0.5).plan(t, e), "server_backup2": waiting.ServerBackup(2).plan(t, e),
        "none": waiting.NoMixing().plan(t, e),
    }
    config = {"k_total": k, "eval_every": 4, "step": "constant", "step_options": {"c": 0.2}}
    parts = [
        compare(spark, ex, plans, model, Config(**config)),
        compare(spark, ex, {"full_mix_first": plans["full"], "cover_mix_first": plans["cover"]}, model, Config(order="mix_first", **config)),
        compare(spark, ex, {"cover_late_discard": plans["cover"]}, model, Config(late="discard", **config)),
        compare(spark, ex, {"fastest2_receiver": waiting.FastestCount(2, "receiver").plan(t, e)}, model, Config(weights="receiver_mean", **config)),
    ]
    h = parts[0]
    for p in parts[1:]:
        h = h.unionByName(p)
    end = h.filter(F.col("k") == k).select("run", "loss", "disagreement", F.col("clock").alias("whole_clock"))
    return end.join(quality.iterations_to(h, "loss", 0.6), "run")


def quality_task(spark, d):
    return tasks.shard(tasks.quality_examples(load(spark, d, "documents"), load(spark, d, "labels")), N)


QUALITY = Softmax(len(tasks.QUALITY_SIGNS) + 1, 2)


@query("w18_quality")
def _(spark, d):
    """Labelled quality by shares of letters and signs: an imbalanced two-class task."""
    return curve(spark, d, quality_task(spark, d), QUALITY)


@query("w18_quality_confusion")
def _(spark, d):
    ex = cut(quality_task(spark, d))
    p, _ = trained(spark, ex, adaptive(spark, d, 60), QUALITY, Config(k_total=60, eval_every=60))
    return quality.confusion(ex.filter("is_test"), p, QUALITY)


@query("w18_quality_unlabelled")
def _(spark, d):
    """The trained classifier on every document without a label."""
    p, _ = trained(spark, quality_task(spark, d), adaptive(spark, d, 60), QUALITY, Config(k_total=60, eval_every=60))
    rest = load(spark, d, "documents").join(load(spark, d, "labels").select("doc_id"), "doc_id", "left_anti").filter("length(text) > 0")
    x = tasks.letter_shares(F.col("text"), tasks.QUALITY_SIGNS)
    rows = rest.select(F.col("doc_id").alias("row_id"), x.alias("x"), F.lit(0).alias("y"))
    return quality.predictions(rows, p, QUALITY).select(F.col("row_id").alias("doc_id"), F.col("predicted").alias("quality"))


def language_model(spark, d):
    """Parameters of the language model after a run under the path cover."""
    ex = tasks.language(spark, d)
    return trained(spark, ex, adaptive(spark, d, 60), Softmax(LETTERS, 4), Config(k_total=60, eval_every=60))[0]


def _rank(c):
    return (F.array_position(F.array(*[F.lit(v) for v in tasks.LANGUAGES]), c) - 1).cast("int")


@query("w19_transfer")
def _(spark, d):
    """The language model on pages, whose markup names their language: confusion."""
    pages = load(spark, d, "pages").select(
        F.col("page_id").alias("row_id"),
        F.regexp_replace("html", "(?s)<(script|style).*?</\\1>|<[^>]*>", " ").alias("text"),
        F.regexp_extract("html", "lang=\"?([a-z]{2})", 1).alias("lang"),
    ).filter(F.col("lang").isin(*tasks.LANGUAGES) & (F.length("text") > 0))
    rows = pages.select("row_id", tasks.letter_shares(F.col("text"), tasks.LETTERS).alias("x"), _rank(F.col("lang")).alias("y"))
    return quality.confusion(rows, language_model(spark, d), Softmax(LETTERS, 4))


@query("w19_transfer_tables")
def _(spark, d):
    """The language model on benchmark items and conversation turns: texts by predicted language."""
    p, out = language_model(spark, d), None
    for name, key in (("benchmark", "item_id"), ("conversations", "conv_id")):
        rows = load(spark, d, name).filter("length(text) > 0")
        rows = rows.select(F.col(key).alias("row_id"), tasks.letter_shares(F.col("text"), tasks.LETTERS).alias("x"), F.lit(0).alias("y"))
        n = quality.predictions(rows, p, Softmax(LETTERS, 4)).groupBy("predicted").agg(F.count(F.lit(1)).alias("n"))
        n = n.withColumn("source", F.lit(name))
        out = n if out is None else out.unionByName(n)
    return out.withColumn("lang", F.element_at(F.array(*[F.lit(v) for v in tasks.LANGUAGES]), F.col("predicted") + 1)).select("source", "lang", "n")


@query("w21_tradeoff")
def _(spark, d):
    """More backups against convergence: q fastest neighbours, full wait and path cover on one clock."""
    t, e = cut(trace(spark, d).filter("k <= 60")), six(spark)
    plans = {f"fastest_{q}": waiting.FastestCount(q).plan(t, e) for q in (0, 1, 2, 3)} | both_plans(spark, d, 60, times=t)
    ex = tasks.language(spark, d, how="by_label")
    return compare(spark, ex, plans, Softmax(LETTERS, 4), Config(k_total=60, eval_every=10))


@query("b08_server_backup_curve")
def _(spark, d):
    t, e = cut(trace(spark, d).filter("k <= 60")), six(spark)
    plans = {"server_sync": waiting.ServerSync().plan(t, e), "server_backup2": waiting.ServerBackup(2).plan(t, e), "none": waiting.NoMixing().plan(t, e)}
    return compare(spark, tasks.language(spark, d), plans, Softmax(LETTERS, 4), Config(k_total=60, eval_every=10))


@query("b11_single_worker")
def _(spark, d):
    """One worker: plain stochastic gradient descent."""
    t = cut(trace(spark, d, 1).filter("k <= 60"))
    plan = {"single": waiting.PathCover([]).plan(t, six(spark).filter("false"))}
    return compare(spark, tasks.language(spark, d, n=1), plan, Softmax(LETTERS, 4), Config(k_total=60, n=1, eval_every=10))


@query("w09_softmax_workers")
def _(spark, d):
    """The revenue tiers with 2 to 25 workers on a ring, batches of 32 rows a worker: both rules."""
    parts = []
    for n in (2, 4, 6, 8, 12, 16, 25):
        links = graphs.graph("ring", n)
        t = cut(law(spark, "exponential", n, 60, 3))
        plans = both_plans(spark, d, 60, graphs.graph("path", n), graphs.edges(spark, links), t)
        ex = tasks.shard(tasks.revenue_examples(load(spark, d, "lineitem")), n)
        o = {"batch": 32, "eval_every": 20, "step": "horizon", "step_options": {"n": n, "last": 60}}
        parts.append((str(n), compare(spark, ex, plans, Softmax(5, 3), Config(k_total=60, n=n, **o))))
    return stacked(parts)


def final(history):
    """Loss, error and clock at the end of each run."""
    last = history.groupBy("run").agg(F.max_by(F.struct("k", "loss", "test_error", "clock"), "k").alias("e"))
    return last.select("run", "e.*")


@query("w01_final")
def _(spark, d):
    """The end of the language curve: both rules, rounded to what is reported."""
    return final(QUERIES["w01_curve"](spark, d)).select("run", "k", rounded("loss", 4).alias("loss"), rounded("test_error", 4).alias("test_error"), rounded("clock", 2).alias("clock"))


@query("w01_train_runs_disagreement")
def _(spark, d):
    """Largest distance of a worker to the mean along the run, for both rules on by-label shards."""
    seen = []

    def watch(k, runs, _):
        seen.extend((r.name, k, float(((r.w - r.w.mean(axis=0)) ** 2).sum(axis=1).max())) for r in runs)

    ex = tasks.language(spark, d, how="by_label")
    train_runs(spark, ex, both_plans(spark, d, 60), Softmax(LETTERS, 4), Config(k_total=60, eval_every=60), watch)
    return spark.createDataFrame(seen, "run string, k int, disagreement double")
