"""Queries on the events trace take all its iterations."""

import numpy as np
import pytest

from consensus_spark.operators import weights
from consensus_spark.plans import schedule_queries, surrounding_queries, training_queries, workload_queries
from consensus_spark.plans.schedule_queries import N, adaptive, trace

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def times(spark):
    rows = trace(spark, SF).collect()
    t = np.zeros((max(r["k"] for r in rows), N))
    for r in rows:
        t[r["k"] - 1, r["worker"]] = r["t"]
    assert len(t) > 200
    return t


def test_server_async(spark, times):
    arrival = np.cumsum(times, axis=0)
    order = sorted((arrival[k, w], w, k) for k in range(len(times)) for w in range(N))
    version = {(w, k): i for i, (_, w, k) in enumerate(order, 1)}
    rows = training_queries.QUERIES["b09_server_async"](spark, SF).collect()
    assert len(rows) == times.size
    late = {(r["worker"], r["k"]): r["staleness"] for r in rows}
    want = {(w, k + 1): v - version.get((w, k - 1), 0) - 1 for (w, k), v in version.items()}
    # sums in another order can swap arrivals that are equal but for rounding
    assert sum(late[x] != want[x] for x in want) <= len(want) // 500


def test_stale_sync(spark, times):
    got = {r["bound"]: r["finished"] for r in training_queries.QUERIES["b10_stale_sync"](spark, SF).collect()}
    for bound in (0, 1, 4):
        f = np.zeros((len(times) + 1, N))
        for k in range(1, len(f)):
            f[k] = np.maximum(f[k - 1], f[max(0, k - 1 - bound)].max()) + times[k - 1]
        assert got[bound] == pytest.approx(f[-1].max())


def test_products_and_tail(spark, times):
    p = adaptive(spark, SF)
    some = weights.metropolis(p.active.filter("k <= 20"), p.times.filter("k <= 20"))
    dense = weights.matrices(some, N)
    assert all((m == dense[k]).all() for k, m in weights.in_order(some, N)) and len(dense) == 20
    tail = workload_queries.QUERIES["w16_tail"](spark, SF).collect()
    assert [r["k"] for r in tail] == list(range(workload_queries.TRAINED + 1, len(times) + 1))
    firsts = [r for r in schedule_queries.QUERIES["a23_positivity"](spark, SF).collect() if r["epochs"] == 1]
    assert len(firsts) == len(times) // 5


def test_stretches(spark, times):
    whole = {r["k"]: r["n"] for r in surrounding_queries.QUERIES["o_range_iterations"](spark, SF).collect()}
    values = surrounding_queries.load(spark, SF, "events").select("value").toPandas()["value"]
    ends = [r["clock"] for r in _clock(spark)]
    assert sum(whole.values()) == ((values > 0) & (values <= ends[-1])).sum()


def _clock(spark):
    from consensus_spark.operators import timing

    s = adaptive(spark, SF).schedule.selectExpr("k", "cutoff AS duration")
    return timing.clock(s).orderBy("k").collect()
