"""Queries take their rows from the given tables: other tables give other results."""

import math

import pytest
from pyspark.sql import functions as F

from consensus_spark import registry
from consensus_spark.sources import graphs
from consensus_spark.sources.tables import EVENTS, load

SF = "/root/testdata/sf0.001"


def events_of(spark, folder, table):
    """An events table whose trace is ``table[iteration][worker]``; returns its folder."""
    day = F.lit("2024-01-01 00:00:00").cast("timestamp_ntz")
    rows = [(k * len(r) + w, k, w, float(t)) for k, r in enumerate(table) for w, t in enumerate(r)]
    e = spark.createDataFrame(rows, "event_id long, k long, user_id long, value double").withColumn("ts", day + F.make_dt_interval(F.lit(0), F.lit(0), F.col("k")))
    e.withColumn("event_type", F.lit("view")).withColumn("props", F.lit("{}")).select(*EVENTS.names).write.parquet(f"{folder}/events.parquet")
    return str(folder)


def rows(spark, folder, name):
    return sorted(tuple(r) for r in registry.QUERIES[name](spark, folder).collect())


#: One iteration of six workers that is cut off at 3: workers 0, 1 and 2 are ready, of whose links only 1-2 is one.
ONE = [(1, 2, 3, 4, 5, 6)]


def test_bound_of_the_events(spark, tmp_path):
    # in hundreds: mean 2, variance 1
    got = rows(spark, events_of(spark, tmp_path, [(100, 300) * 3] * 2), "a16_bound")
    assert [r[0] for r in got] == [1, 2]
    assert [r[1:] for r in got] == [pytest.approx((4 / (0.1 * k) + 0.0025 / 12, 4 / (0.1 * k) + 0.05 / 12), abs=1e-9) for k in (1, 2)]


def test_gradient_bound_of_the_events(spark, tmp_path):
    from consensus_spark.operators import theory

    # in hundreds: mean 2, variance 1; six users in two iterations make 6 of two workers and 4 of three
    got = rows(spark, events_of(spark, tmp_path, [(100, 300) * 3] * 2), "a15_gradient_bound")
    assert [r[:3] for r in got] == [(2, 1, 0.5), (3, 2, pytest.approx(1 / 3))]
    for (n, b, beta, _, bound), last in zip(got, (6, 4), strict=True):
        assert bound == pytest.approx(theory.gradient_bound(last, 2.0, 0.05, 1.0, n, b, beta, 1.0))


def test_control_messages_of_the_trace(spark, tmp_path):
    got = {r[0]: r for r in rows(spark, events_of(spark, tmp_path, ONE * 3), "a26_control")}
    # with four workers, two of the six users fall to each of the first two
    assert got[4] == (4, 3, 8, 24, 3, 3, 24) and got[2] == (2, 1, 4, 4, 1, 9, 36) and got[7][5:] == (0, 0)


def test_degrees_of_the_links_used(spark, tmp_path):
    assert rows(spark, events_of(spark, tmp_path, ONE), "g_degrees") == [(1, 1), (2, 1)]
    assert rows(spark, SF, "g_degrees") == [(0, 2), (1, 2), (2, 3), (3, 3), (4, 4), (5, 2)]


def test_reach_over_the_links_used(spark, tmp_path):
    assert rows(spark, events_of(spark, tmp_path, ONE), "g_reachable") == [(0, 0)]
    assert rows(spark, SF, "g_reachable") == [(0, 0), (1, 2), (2, 2), (3, 1), (4, 1), (5, 2)]


def test_covers_by_the_times_of_the_trace(spark, tmp_path):
    got = {r[:2]: r for r in rows(spark, events_of(spark, tmp_path, [(6, 5, 4, 3, 2, 1), (8, 5, 4, 3, 2, 1)]), "m10_covers")}
    assert len(got) == 28 and all(r[3] for r in got.values())
    # worker 5 is the fastest: its links are the quickest for every other worker
    assert got["complete", "min_time_tree"][4:] == (str([(4, 5), (3, 4), (2, 3), (1, 2), (0, 1)]), (2 + 3 + 4 + 5 + 7) / 5)
    assert got["star", "tree"][5] == 7


def test_worked_example_from_events(spark, tmp_path):
    """The hand-checked rows, with times twice as long."""
    from consensus_spark.plans.schedule_queries import GOLDEN_TIMES

    folder = events_of(spark, tmp_path, [[2 * t for t in r] for r in GOLDEN_TIMES])
    assert rows(spark, folder, "m11_golden") == [(1, 0, 1, 2, 6.0, 1), (2, 0, 2, 0, 4.0, 1), (3, 0, 3, 1, 6.0, 1)]


def test_sets_of_the_links_used(spark, tmp_path):
    assert rows(spark, events_of(spark, tmp_path, ONE), "o_set_ops_links") == [(1, 2, "on_cover")]
    whole = rows(spark, SF, "o_set_ops_links")
    assert [r[:2] for r in whole] == sorted(graphs.SIX) and {r[:2] for r in whole if r[2] == "on_cover"} == set(graphs.SIX_COVER)


def test_constant_steps_of_the_trace(spark, tmp_path):
    assert rows(spark, events_of(spark, tmp_path, ONE * 3), "r1_constant") == [(1, 0.05), (2, 0.05), (3, 0.05)]


def test_iterations_required_by_events(spark, tmp_path):
    # means in hundreds of the first one, two and three workers: 0.6, 0.4, 0.5
    tol = [0.125 * 0.5 * m * m for m in (0.6, 0.4, 0.5)]
    got = rows(spark, events_of(spark, tmp_path, [(40, 30, 70), (80, 10, 70)]), "a17_required")
    assert got == [(n, math.ceil(1 / (t * t * n))) for n, t in enumerate(tol, 1)]
