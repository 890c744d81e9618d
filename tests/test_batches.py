"""Mini-batches, both state regimes, moments, components and the workloads built on them."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from consensus_spark.operators import mixing, moments, tail
from consensus_spark.operators.models import LeastSquares, Softmax
from consensus_spark.operators.waiting import FullWait, PathCover
from consensus_spark.plans import tasks, trainer
from consensus_spark.plans.speedup_queries import QUERIES as SPEEDUP
from consensus_spark.plans.trainer import Config, Slots, compare, relational_train, trained
from consensus_spark.sources import graphs
from consensus_spark.sources.times import law

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def language(spark):
    return tasks.language(spark, SF, tasks.SMALL_LETTERS).cache()


@pytest.fixture(scope="module")
def plans(spark):
    t, e = law(spark, "exponential", 6, 130, 2).cache(), graphs.edges(spark, graphs.SIX)
    return {"full": FullWait().plan(t, e), "adaptive": PathCover(graphs.SIX_COVER).plan(t, e)}


def test_slots_hold_a_batch_and_every_regime_agrees(spark, language, plans, monkeypatch):
    model, config = Softmax(7, 4), Config(k_total=4, eval_every=4, batch=8)
    train = language.filter("NOT is_test")
    slots = Slots(train, config)
    assert slots.count == train.count() // 48 > 2
    assert sum(slots.frame(k).count() for k in range(1, min(4, slots.count) + 1)) <= train.count()
    held = trained(spark, language, plans["adaptive"], model, config)[1]
    monkeypatch.setattr(trainer, "PREFETCH_BYTES", 0)
    scanned = trained(spark, language, plans["adaptive"], model, config)[1]
    monkeypatch.setattr(trainer, "PARTIAL_BYTES", 0)
    summed = trained(spark, language, plans["adaptive"], model, config)[1]
    rows = relational_train(spark, slots.frame, plans["adaptive"], model, config).collect()
    wide = np.zeros_like(held)
    for r in rows:
        wide[r["worker"], r["idx"]] = r["val"]
    for other in (scanned, summed, wide):
        assert np.allclose(held, other, atol=1e-12)


def test_long_run_ends_where_full_wait_ends_and_sooner(spark, plans):
    ex = tasks.language(spark, SF)
    h = compare(spark, ex, plans, Softmax(38, 4), Config(k_total=120, eval_every=120))
    end = {r["run"]: r for r in h.filter("k = 120").collect()}
    assert end["adaptive"]["loss"] == pytest.approx(end["full"]["loss"], abs=0.03) and end["full"]["loss"] < 0.25
    assert end["adaptive"]["clock"] < 0.6 * end["full"]["clock"]


@pytest.mark.parametrize("step, options", [("per_worker", {"steps": [0.1] * 6}), ("batch_proportional", {"c": 0.2})])
def test_steps_of_workers_and_of_participation(spark, language, plans, step, options):
    config = Config(k_total=3, eval_every=3, step=step, step_options=options)
    w = trained(spark, language, plans["adaptive"], Softmax(7, 4), config)[1]
    assert np.isfinite(w).all() and np.abs(w).max() > 0
    if step == "per_worker":
        same = trained(spark, language, plans["adaptive"], Softmax(7, 4), Config(k_total=3, eval_every=3, step="constant", step_options={"c": 0.1}))[1]
        assert np.allclose(w, same)
    else:
        assert config.step_at(1, {0, 1, 2})[0] == pytest.approx(0.1)


@pytest.mark.parametrize("model", [Softmax(7, 4), LeastSquares(7)])
def test_gradient_by_place_equals_broadcast(spark, language, model, monkeypatch):
    w = np.random.default_rng(0).normal(size=(6, model.size))
    params = spark.createDataFrame([(j, i, float(v)) for j, r in enumerate(w) for i, v in enumerate(r)], "worker int, idx int, val double")
    read = lambda df: {(r["worker"], r["idx"]): r["g"] for r in df.collect()}
    one = read(mixing.local_gradient(language, params, model))
    monkeypatch.setattr(mixing, "BROADCAST_BYTES", 0)
    two = read(mixing.local_gradient(language, params, model))
    monkeypatch.undo()
    monkeypatch.setattr(mixing, "WIDE", 0)
    three = read(mixing.local_gradient(language, params, model))
    assert one.keys() == two.keys() == three.keys()
    assert all(one[k] == pytest.approx(two[k], abs=1e-9) == pytest.approx(three[k], abs=1e-9) for k in one)


def test_components_and_bigrams(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(60).withColumn("row_id", F.col("doc_id"))
    got = {r["row_id"]: r["x"] for r in tasks.bigram_examples(docs, 16).collect()}
    want = docs.filter("length(text) > 1").select("row_id", tasks.bigram_hash(F.col("text"), 16).alias("x"))
    for r in want.collect():
        assert np.allclose(got[r["row_id"]], r["x"])
    rng = np.random.default_rng(4)
    x = rng.normal(size=(200, 5)) @ rng.normal(size=(5, 5)) + 3
    ex = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id long, x array<double>")
    pca = tasks.Pca.fit(ex, 5, 2)
    values = np.sort(np.linalg.eigvalsh(np.cov(x.T, bias=True)))[::-1]
    assert np.allclose(pca.share, values[:2] / values.sum())
    out = np.array([r["x"] for r in pca.apply(ex).orderBy("row_id").collect()])
    assert np.allclose(out[:, :2] * pca.scale, (x - x.mean(axis=0)) @ pca.directions) and (out[:, 2] == 1).all()


def test_moments_train_as_rows_do(spark):
    rng = np.random.default_rng(5)
    x, y = rng.normal(size=(240, 3)), rng.normal(size=240)
    rows = [(i % 12, x[i].tolist(), float(y[i])) for i in range(240)]
    table = moments.batch_moments(spark.createDataFrame(rows, "batch int, x array<double>, y double"), 3)
    m, model = moments.Moments.fetch(table, 12, 3), LeastSquares(3)
    mat = np.array([[0.5, 0.5], [0.5, 0.5]])
    w = np.zeros((2, 3))
    for k, got in moments.synchronous(m, 2, 9, 0.1, mat):
        at = [np.arange(240) % 12 == ((k - 1) * 2 + i) % 12 for i in range(2)]
        w = mat.T @ (w - 0.1 * np.array([model.grad_sum(w[i], x[a], y[a]) / a.sum() for i, a in enumerate(at)]))
        assert np.allclose(w, got)
    assert m.loss(w[0]) == pytest.approx(model.loss_sum(w[0], x, y) / 240)
    assert m.loss(m.best()) < m.loss(w[0])


def test_servers_that_do_not_wait():
    m = moments.Moments(np.ones(8), np.tile(np.eye(2), (8, 1, 1)), np.ones((8, 2)), np.full(8, 2.0))
    steps = list(moments.asynchronous(m, [(0, 1), (1, 1), (0, 2), (0, 3), (1, 2)], 2, 0.5))
    assert [s for _, s, _ in steps] == [0, 1, 1, 0, 2]
    # gradients at 0, 0, 0.5, 1.25 and 0.5 + 0.5 (read after the second update)
    assert [float(w[0]) for *_, w in steps] == pytest.approx([0.5, 1.0, 1.25, 1.125, 1.125])
    # with bound 0 all start together: exact averaging
    full = list(moments.bounded_staleness(m, iter([(k, [1.0, 3.0]) for k in (1, 2, 3)]), 2, 0, 0.5))
    assert [c for _, c, _ in full] == [3.0, 6.0, 9.0] and np.allclose(full[-1][2], 1 - 0.5**3)
    loose = list(moments.bounded_staleness(m, iter([(k, [1.0, 3.0]) for k in (1, 2, 3)]), 2, 2, 0.5))
    assert loose[-1][1] == 9.0 and np.isfinite(loose[-1][2]).all()


def test_more_workers_need_fewer_iterations(spark):
    rows = {r["n"]: r for r in SPEEDUP["a13_speedup"](spark, "/root/testdata/sf0.01").collect()}
    assert rows[25]["speedup"] > rows[8]["speedup"] > rows[4]["speedup"] > rows[2]["speedup"] == 1.0
    slope = SPEEDUP["a14_rate_fit"](spark, "/root/testdata/sf0.01").first()["slope"]
    assert slope < -0.5


def test_tail_agrees_at_the_mean():
    rng = np.random.default_rng(0)
    m = np.array([[0.5, 0.5, 0], [0.5, 0.25, 0.25], [0, 0.25, 0.75]])
    rows, first = tail.iterations_to_agree(rng.normal(size=(3, 2)), [m] * 200, [1e-2, 1e-6])
    assert first[1e-2] < first[1e-6] == rows[-1][0] and rows[-1][2] < 1e-12
