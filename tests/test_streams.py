"""Streams against the same work in one batch."""

import datetime as dt

from pyspark.sql import functions as F

from localcomm import sources
from localcomm.operators import partition as pa
from localcomm.params import Params
from localcomm.plans.surroundings import _interval
from localcomm.streaming import events as st


def _events(spark, path):
    t = dt.datetime(2024, 1, 1, 10)
    rows = [(i, t + dt.timedelta(minutes=i % 50), 1 + i % 6, "view", 1.0, f'{{"k": {i % 6 // 3 if i < 30 else 2}}}') for i in range(34)]
    df = spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string")
    df.coalesce(1).write.parquet(f"{path}/events.parquet")
    return df


def test_refreshed_seeds_are_partitions(spark, tmp_path):
    _events(spark, tmp_path)
    g = sources.users(spark, str(tmp_path))
    seeds = g.nodes.select(F.col("node").alias("seed"))
    want = pa.attributed_partition(g.combined(), seeds, g.nodes.count(), Params(stop="fixed")).summary
    rows = lambda df: sorted((r["seed"], r["size"], r["target_met"]) for r in df.collect())
    got = st.refresh_seeds(spark, str(tmp_path))
    assert got.columns == ["seed", "size", "score", "target_met"] and rows(got) == rows(want)


def test_pairs_within_ten_minutes(spark):
    t = dt.datetime(2024, 1, 1)
    ev = spark.createDataFrame([(1, 1, "p", t), (2, 2, "p", t + dt.timedelta(seconds=600)), (3, 3, "p", t + dt.timedelta(seconds=1201))], "event_id long, user_id long, props string, ts timestamp_ntz")
    assert [tuple(r) for r in _interval(ev, 600).collect()] == [(1, 2)]
