"""Replayed streams: where their rows go and what they read."""

import math
import random
import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from consensus_spark.operators.schedule import path_cover_schedule
from consensus_spark.plans import surrounding_queries
from consensus_spark.plans.schedule_queries import N
from consensus_spark.sources import graphs
from consensus_spark.sources.times import trace_from_events
from consensus_spark.sources.tables import EVENTS, load
from consensus_spark.streaming import completions as S

SF = "/root/testdata/sf0.001"


def test_appended_rows_stay_off_the_driver(spark):
    s = spark.readStream.schema(EVENTS).parquet(f"{SF}/events.parque[t]").select("event_id")
    rows = S.replay(s, f"s{uuid.uuid4().hex}")
    assert rows.inputFiles() and rows.count() == load(spark, SF, "events").count()


@pytest.mark.parametrize("name", ["o_stream_dedup"])
def test_events_in_a_folder(spark, tmp_path, name):
    e = load(spark, SF, "events")
    e.union(e.filter("event_id < 100")).repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    got = surrounding_queries.QUERIES[name](spark, str(tmp_path))
    assert sorted(got.collect()) == sorted(surrounding_queries.QUERIES[name](spark, SF).collect()) != []
    assert got.first()[0] == e.count()


def test_links_are_picked_as_one_by_one():
    rng = random.Random(3)
    some = [1.0, 2.0, 3.0, 0.0, -0.0, -1.5, math.inf, -math.inf, math.nan]
    for _ in range(200):
        d, m = rng.randint(1, 5), rng.randint(1, 30)
        used = rng.sample(range(d), rng.randint(0, d - 1))
        table, want, left = [[rng.choice(some) for _ in range(d)] for _ in range(m)], [], list(used)
        for r in table:
            want.append(min((math.isnan(r[i]), 0 if math.isnan(r[i]) else r[i], i) for i in range(d) if i not in left)[2])
            left = [] if len(left) == d - 1 else [*left, want[-1]]
        lid, rest = S._pick(S._in_order(np.array(table)), used)
        assert lid.tolist() == want and rest == left


def test_schedule_over_batches_with_events_without_a_value(spark, tmp_path):
    e = load(spark, SF, "events").withColumn("value", F.when(F.col("event_id") % 7 > 0, F.col("value")))
    third = e.withColumn("part", F.ntile(3).over(surrounding_queries.W.orderBy("ts", "event_id"))).cache()
    for i in (1, 2, 3):  # files come in the order of their time
        third.filter(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
    s = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/events.parquet")
    name = f"s{uuid.uuid4().hex}"
    got = S.replay(S.stream_path_cover(S.completions(s, N), N, graphs.SIX, graphs.SIX_COVER), name).select("k", "lid", "cutoff")
    want = path_cover_schedule(trace_from_events(e, N), graphs.SIX_COVER).select("k", "lid", "cutoff")
    assert sorted(got.collect()) == sorted(want.collect()) != []
