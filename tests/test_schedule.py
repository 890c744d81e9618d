"""Schedules, wait sets, weights and measures: the worked example and the invariants."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from consensus_spark.operators import connectivity, theory, timing, waiting, weights
from consensus_spark.operators.cover import find_cover
from consensus_spark.operators.schedule import clairvoyant_cost, exact_min_wait, path_cover_schedule
from consensus_spark.plans.schedule_queries import GOLDEN_TIMES, golden
from consensus_spark.sources import graphs
from consensus_spark.sources.tables import TIMES


def frame(spark, table):
    return spark.createDataFrame([(k + 1, w, float(t)) for k, r in enumerate(table) for w, t in enumerate(r)], TIMES)


def plan_of(spark, table, links, cover, **o):
    return waiting.PathCover(cover, **o).plan(frame(spark, table), graphs.edges(spark, links))


def by_hand(table, cover):
    """Cutoffs of the rule, one iteration after another."""
    used, out = set(), []
    for r in table:
        c, lid = min((max(r[a], r[b]), i) for i, (a, b) in enumerate(cover) if i not in used)
        used.add(lid)
        out.append((lid, c))
        if len(used) == len(cover):
            used = set()
    return out


def test_worked_example(spark):
    p = waiting.PathCover(graphs.FOUR_COVER).plan(golden(spark), graphs.edges(spark, graphs.FOUR))
    s = sorted(p.schedule.collect())
    assert [(r["lid"], r["cutoff"]) for r in s] == [(2, 3.0), (0, 2.0), (1, 3.0)]
    wait = {(r["k"], r["worker"]): r for r in p.wait().collect()}
    assert [[wait[k, w]["n_wait"] for w in range(4)] for k in (1, 2, 3)] == [[1, 0, 2, 1], [1, 1, 0, 0], [0, 1, 2, 1]]
    assert [[wait[k, w]["n_backup"] for w in range(4)] for k in (1, 2, 3)] == [[1, 2, 1, 0], [1, 1, 3, 1], [2, 1, 1, 0]]
    m = weights.matrices(weights.metropolis(p.active, p.times), 4)
    v = np.array([1.0, 2, 3, 4])
    for k, want in ((1, [5 / 3, 2, 8 / 3, 11 / 3]), (2, [11 / 6, 11 / 6, 8 / 3, 11 / 3]), (3, [11 / 6, 19 / 9, 49 / 18, 10 / 3])):
        v = m[k].T @ v
        assert np.allclose(v, want)
    product = {(r["src"], r["dst"]): r["w"] for r in weights.mix_product(weights.metropolis(p.active, p.times), 1, 3).collect()}
    assert np.allclose([product[0, j] for j in range(4)], [1 / 3, 1 / 3, 2 / 9, 1 / 9])
    full = timing.iteration_duration(waiting.full_active(p.times, p.edges), p.times)
    r = timing.duration_reduction(full, timing.iteration_duration(p.active, p.times)).first()
    assert r["reduction"] == pytest.approx(7 / 15)
    table = [[max(t[a], t[b]) for a, b in graphs.FOUR_COVER] for t in GOLDEN_TIMES]
    assert clairvoyant_cost(table, "one_link_each") == 8


def test_ties_and_engines(spark):
    one = path_cover_schedule(frame(spark, [(1, 3, 2, 9)]), graphs.FOUR_COVER).first()
    assert (one["lid"], one["n_tied"]) == (0, 2)
    both = path_cover_schedule(frame(spark, [(1, 3, 2, 9), (1, 1, 1, 2)]), graphs.FOUR_COVER, ties="all").orderBy("k").collect()
    assert [(r["epoch"], r["lid"], r["n_tied"]) for r in both] == [(0, 0, 2), (0, 2, 1)]
    rng = random.Random(1)
    table = [[rng.expovariate(1) for _ in range(6)] for _ in range(23)]
    t = frame(spark, table)
    fold = sorted(path_cover_schedule(t, graphs.SIX_COVER).collect())
    assert fold == sorted(path_cover_schedule(t, graphs.SIX_COVER, engine="pandas").collect())
    assert [(r["lid"], r["cutoff"]) for r in fold] == by_hand(table, graphs.SIX_COVER)
    warm = path_cover_schedule(t, graphs.SIX_COVER, warmup_full=True).orderBy("k").collect()
    assert warm[0]["cutoff"] == max(table[0]) and [r["cutoff"] for r in warm[1:]] == [c for _, c in by_hand(table[1:], graphs.SIX_COVER)]


@pytest.mark.parametrize("seed", range(3))
def test_invariants_on_random_graphs(spark, seed):
    rng = random.Random(seed)
    n = rng.randint(3, 7)
    links = graphs.graph("random", n, seed)
    cover = find_cover(links, n, "hamiltonian", seed)
    d = len(cover)
    last = d * (n + 1)
    table = [[rng.expovariate(1) for _ in range(n)] for _ in range(last)]
    p = plan_of(spark, table, links, cover)
    m = weights.matrices(weights.metropolis(p.active, p.times), n)
    wait = p.wait().collect()
    for k, a in m.items():
        assert np.allclose(a, a.T) and np.allclose(a.sum(axis=0), 1) and (a >= -1e-12).all()
        assert a[a > 1e-12].min() >= 1 / n - 1e-12
        q = {r["worker"]: r["n_wait"] for r in wait if r["k"] == k}
        assert all(a[w, w] >= 1 / (1 + q[w]) - 1e-12 for w in range(n))
    degree = [len(s) for s in graphs.neighbours(links, n)]
    assert all(r["n_wait"] + r["n_backup"] == degree[r["worker"]] for r in wait)
    dur = {r["k"]: r["duration"] for r in timing.iteration_duration(p.active, p.times).collect()}
    cut = {r["k"]: r["cutoff"] for r in p.schedule.collect()}
    assert all(dur[k] == cut[k] <= max(table[k - 1]) for k in cut)
    assert all(r["connected"] for r in connectivity.bounded_connectivity(p.active, n, last, d, "aligned").collect())
    assert all(r["connected"] for r in connectivity.bounded_connectivity(p.active, n, last, 2 * d - 1, "sliding").collect())
    assert all(low > 0 and low >= bound for _, low, bound in connectivity.positivity(m, d, n))


def test_policies_order(spark):
    rng = random.Random(5)
    table = [[rng.expovariate(1) for _ in range(6)] for _ in range(30)]
    t, e = frame(spark, table), graphs.edges(spark, graphs.SIX)
    mean = lambda plan: timing.duration_estimate(timing.iteration_duration(plan.active, t)).first()["estimate"]
    by_q = [mean(waiting.FastestCount(q).plan(t, e)) for q in range(4)]
    assert by_q == sorted(by_q) and by_q[0] == 0
    assert waiting.FastestCount(9).plan(t, e).active.count() == waiting.FullWait().plan(t, e).active.count()
    by_c = [mean(waiting.FixedCutoff(c).plan(t, e)) for c in (0.5, 1.0, 2.0)]
    assert by_c == sorted(by_c)
    equal = plan_of(spark, [[2.0] * 6] * 5, graphs.SIX, graphs.SIX_COVER)
    assert equal.active.count() == 5 * 16
    taken = waiting.ServerBackup(2).taken(t)
    assert {r["n"] for r in taken.filter("on_time").groupBy("k").agg(F.count(F.lit(1)).alias("n")).collect()} == {4}


def test_covers_and_graphs():
    for kind in ("random", "ring", "path", "star", "complete", "tree", "grid", "regular"):
        for n in (2, 3, 6):
            links = graphs.graph(kind, n, 2)
            for cover in ("hamiltonian", "tree", "walk"):
                c = find_cover(links, n, cover, 3)
                assert graphs.is_connected(c, n) and set(c) <= set(links) and len(set(c)) == len(c)
    assert find_cover([], 1) == [] and find_cover([(0, 1)], 2) == [(0, 1)]
    with pytest.raises(ValueError):
        find_cover([(0, 1)], 3)
    path = find_cover(graphs.SIX, 6)
    assert any(all({a, b} <= {x, y} for (a, b), (x, y) in zip(path, zip(p, p[1:], strict=False), strict=True)) for p in itertools.permutations(range(6)))
    assert graphs.diameter(graphs.SIX, 6) == 2


def test_clairvoyant_bounds():
    rng = random.Random(2)
    for _ in range(30):
        table = [[rng.expovariate(1) for _ in range(4)] for _ in range(4)]
        one, free = clairvoyant_cost(table, "one_link_each"), clairvoyant_cost(table, "free")
        assert one == pytest.approx(min(sum(table[i][p[i]] for i in range(4)) for p in itertools.permutations(range(4))))
        assert free <= one + 1e-12
    times = [(1.0, 4.0, 2.0, 3.0), (2.0, 2.0, 5.0, 1.0), (6.0, 3.0, 1.0, 2.0)]
    assert exact_min_wait(times, graphs.FOUR, 4, 3) <= 8


def test_theory_numbers():
    assert theory.min_iterations_for_bound(2, 1, 0.5, 0.01) == pytest.approx(18.0, abs=0.05)
    assert theory.min_iterations_for_bound(3, 2, 1 / 3, 0.01) == pytest.approx(10068.6, abs=1)
    assert theory.speedup({2: 100, 4: 50}) == [(2, 100, 1.0), (4, 50, 2.0)]


def test_clock_and_best_constant(spark):
    rows = [(k, float(k % 7) + 0.5) for k in range(1, 9001)]
    d = spark.createDataFrame(rows, "k int, duration double")
    run = timing.clock(d).orderBy("k").collect()
    assert run[-1]["clock"] == pytest.approx(sum(x for _, x in rows)) and run[10]["clock"] == pytest.approx(sum(x for _, x in rows[:11]))
    best = timing.duration_estimate(d).first()
    for guess in np.linspace(0, 7, 15):
        assert timing.duration_mse(d, float(guess)).first()["mse"] >= best["mse"] - 1e-9


def test_server_policies_count_backups_among_all_workers(spark):
    t = spark.createDataFrame([(1, w, float(w)) for w in range(4)], "k int, worker int, t double")
    e = spark.createDataFrame([(0, 1), (1, 0), (1, 2), (2, 1), (2, 3), (3, 2)], "src int, dst int")
    mean = lambda p: p.plan(t, e).wait().agg({"n_backup": "avg"}).first()[0]
    assert mean(waiting.ServerSync()) == 0
    # the two in time wait for one another, the late two for nobody
    assert mean(waiting.ServerBackup(2)) == 2.5
