"""Models, training and the mixing-only phase."""

import numpy as np
import pytest

from consensus_spark.operators import mixing, tail
from consensus_spark.operators.models import LeastSquares, Mlp, Quadratic, Softmax
from consensus_spark.operators.waiting import FullWait, NoMixing, PathCover
from consensus_spark.plans import tasks
from consensus_spark.plans.trainer import Config, compare, relational_train
from consensus_spark.sources import graphs
from consensus_spark.sources.times import law, trace_from_events

SF = "/root/testdata/sf0.01"


@pytest.mark.parametrize("model", [Softmax(4, 3), LeastSquares(4), Mlp(4, 3, (5, 4)), Quadratic()])
def test_gradients_by_differences(model):
    rng = np.random.default_rng(1)
    x, w = rng.normal(size=(7, 4)), rng.normal(size=model.size) * 0.3
    y = rng.normal(size=7) if isinstance(model, LeastSquares | Quadratic) else rng.integers(0, 3, 7)
    g, eps = model.grad_sum(w, x, y), 1e-6
    for i in range(model.size):
        e = np.zeros(model.size)
        e[i] = eps
        assert g[i] == pytest.approx((model.loss_sum(w + e, x, y) - model.loss_sum(w - e, x, y)) / (2 * eps), abs=1e-4)


@pytest.fixture(scope="module")
def language(spark):
    return tasks.language(spark, SF, tasks.SMALL_LETTERS).cache()


@pytest.fixture(scope="module")
def plans(spark):
    t = trace_from_events(spark.read.parquet(f"{SF}/events.parquet"), 6).filter("k <= 40").cache()
    e = graphs.edges(spark, graphs.SIX)
    return {"full": FullWait().plan(t, e), "adaptive": PathCover(graphs.SIX_COVER).plan(t, e), "none": NoMixing().plan(t, e)}


def test_relational_equals_arrow_gradient(spark, language):
    model = Softmax(7, 4)
    w = np.random.default_rng(0).normal(size=(6, model.size))
    params = spark.createDataFrame([(j, i, float(v)) for j, r in enumerate(w) for i, v in enumerate(r)], "worker int, idx int, val double")
    a = {(r["worker"], r["idx"]): r["g"] for r in mixing.local_gradient(language, params, model).collect()}
    b = {(r["worker"], r["idx"]): r["g"] for r in mixing.arrow_gradient(language, {j: w[j] for j in range(6)}, model).collect()}
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-9 for k in a)


def test_both_state_regimes_agree(spark, language, plans):
    model, config = Softmax(7, 4), Config(k_total=2, eval_every=2)
    train = language.filter("NOT is_test")
    p = relational_train(spark, lambda _: train, plans["adaptive"], model, config)
    spread = mixing.disagreement(p).first()["largest"]
    h = compare(spark, language, {"adaptive": plans["adaptive"]}, model, config).filter("k = 2").first()
    assert h["disagreement"] == pytest.approx(spread, rel=1e-9)


def test_adaptive_is_as_good_and_faster(spark, language, plans):
    h = {(r["run"], r["k"]): r for r in compare(spark, language, plans, Softmax(7, 4), Config(k_total=12, eval_every=12)).collect()}
    full, own, none = (h[r, 12] for r in ("full", "adaptive", "none"))
    assert own["loss"] == pytest.approx(full["loss"], rel=0.05)
    assert own["clock"] < 0.6 * full["clock"]
    assert full["disagreement"] < own["disagreement"] < none["disagreement"]


def test_reduction_on_the_trace(spark):
    from consensus_spark import registry

    r = registry.QUERIES["a06_reduction"](spark, SF).first()
    assert 0.55 < r["reduction"] < 0.70


def test_tail_reaches_the_mean(spark):
    links = graphs.graph("ring", 5)
    t, e = law(spark, "uniform", 5, 1, 1), graphs.edges(spark, links)
    from consensus_spark.operators import weights

    m = weights.matrices(weights.metropolis(FullWait().plan(t, e).active, t), 5)[1]
    params = spark.createDataFrame([(w, 0, float(w)) for w in range(5)], "worker int, idx int, val double")
    out, used = tail.consensus_phase(spark, params, [m] * 500, 1e-10)
    assert all(abs(r["val"] - 2.0) < 1e-8 for r in out.collect()) and used < 500


def test_unrolled_and_shadow_mean():
    rng = np.random.default_rng(3)
    m = [np.full((3, 3), 1 / 3), np.array([[0.5, 0.5, 0], [0.5, 0.5, 0], [0, 0, 1]])]
    w0, grads, steps = rng.normal(size=(3, 2)), [rng.normal(size=(3, 2)) for _ in m], [0.1, 0.2]
    w = w0
    for g, s, a in zip(grads, steps, m, strict=True):
        w = a.T @ (w - s * g)
    assert np.allclose(tail.unrolled(w0, grads, steps, m), w)
    assert np.allclose(tail.mean_iterate(w0, grads, steps), w.mean(axis=0))


def test_shards_batches_and_cleaning(spark, language):
    for how, o in (("by_label", {}), ("dirichlet", {"n_classes": 4}), ("sizes", {"sizes": [1, 1, 4]})):
        s = tasks.shard(language.drop("worker"), 3, how, **o)
        assert s.count() == language.count() and {r[0] for r in s.select("worker").distinct().collect()} <= {0, 1, 2}
    b = tasks.draw_batch(language, 2, 20)
    assert {r["count"] for r in b.groupBy("worker").count().collect()} == {20}
    assert tasks.draw_batch(language, 2, 10_000).count() == language.count()
    dirty = spark.createDataFrame([(1, [1.0, None], 0), (2, [float("nan"), 1.0], 0), (3, [1.0, 2.0], 1)], "row_id long, x array<double>, y int")
    assert tasks.clean_examples(dirty).count() == 1
    assert [r["x"] for r in tasks.clean_examples(dirty, "zero").orderBy("row_id").collect()][0] == [1.0, 0.0]


def test_stream_equals_batch(spark):
    from consensus_spark import registry

    key = lambda df: sorted((r["k"], r["lid"], r["cutoff"]) for r in df.collect())
    assert key(registry.QUERIES["o_stream_schedule"](spark, "/root/testdata/sf0.001")) == key(
        registry.QUERIES["m11_schedule"](spark, "/root/testdata/sf0.001")
    )


def test_slots_on_disk(spark, language, tmp_path):
    from consensus_spark.sources.tables import read_slot, save_slots

    save_slots(tasks.assign_slots(language, 4), str(tmp_path / "slots"))
    one = read_slot(spark, str(tmp_path / "slots"), 2)
    assert one.count() == tasks.assign_slots(language, 4).filter("slot = 2").count()
    assert "PartitionFilters: [isnotnull(slot" in one._jdf.queryExecution().toString()
