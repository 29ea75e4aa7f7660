"""Structured Streaming over the events: windows, sessions, deduplication, running degrees, refreshed partitions.

Each stream reads the events as files, runs to the end of what is there (`availableNow`) and leaves its result in a
table of the shared folder; the batch twin of a window query says what must come out.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcomm.plans.stages import shared_root


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files, with a timestamp that watermarks accept."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "*events*.parquet" if not _folder(spark, f"{sf_dir}/events.parquet") else "*.parquet")
    path = f"{sf_dir}/events.parquet" if _folder(spark, f"{sf_dir}/events.parquet") else sf_dir
    return stream.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def _folder(spark: SparkSession, path: str) -> bool:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(where).isDirectory()


def drained(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run the stream over all that is there and read what it wrote."""
    spark = df.sparkSession
    root = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").outputMode(mode).trigger(availableNow=True).start()
    else:
        def last(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{root}/out")

        q = df.writeStream.foreachBatch(last).option("checkpointLocation", f"{root}/state").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{root}/out")


def _count(df: DataFrame, window) -> DataFrame:
    return df.groupBy(window.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "user_id", "events")


DELAY = "10 minutes"


def tumbling(s, d):
    return drained(_count(source(s, d).withWatermark("ts", DELAY), F.window("ts", "1 hour")), "tumbling")


def sliding(s, d):
    return drained(_count(source(s, d).withWatermark("ts", DELAY), F.window("ts", "1 hour", "30 minutes")), "sliding")


def session(s, d):
    return drained(_count(source(s, d).withWatermark("ts", DELAY), F.session_window("ts", "30 minutes")), "session")


def dedup(s, d):
    """Events once each; repeats are known for two days of event time, then their state goes."""
    return drained(source(s, d).withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), "dedup")


def arrived_late(s, d) -> tuple[DataFrame, int]:
    """Closed hourly windows when the later half of the time comes first, and how many groups of rows the watermark rejected."""
    e = s.read.parquet(f"{d}/events.parquet")
    at = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000)
    lo, hi = e.agg(F.min(at), F.max(at)).first()
    root, late = f"{shared_root(s)}/late-{uuid.uuid4().hex}", 0
    mid = ((lo or 0) + (hi or 0)) // 2
    for half in (at >= mid, at < mid):
        e.where(half).write.mode("append").parquet(f"{root}/in")
        counted = _count(s.readStream.schema(e.schema).parquet(f"{root}/in").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", DELAY), F.window("ts", "1 hour"))
        q = counted.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        late += sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    return s.read.parquet(f"{root}/out"), late


def late_drop(s, d):
    """What is left when late rows are dropped: see `arrived_late`."""
    return arrived_late(s, d)[0]


def static_join(s, d):
    kinds = s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return drained(source(s, d).join(kinds, "user_id").select("event_id", "user_id", "c_mktsegment"), "static")


def degree_state(s, d):
    """Running number of distinct props per user, kept as state."""

    def update(key, frames, state):
        seen = set(state.get[0]) if state.exists else set()
        for f in frames:
            seen |= set(f["props"])
        state.update((sorted(seen),))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [len(seen)]})

    out = source(s, d).groupBy("user_id").applyInPandasWithState(update, "user_id long, degree long", "seen array<string>", "update", "NoTimeout")
    root = f"{shared_root(s)}/degree-{uuid.uuid4().hex}"
    q = out.writeStream.foreachBatch(lambda b, i: b.withColumn("batch", F.lit(i)).write.mode("append").parquet(f"{root}/out")).option("checkpointLocation", f"{root}/state").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.parquet(f"{root}/out").groupBy("user_id").agg(F.max_by("degree", "batch").alias("degree"))


def refresh_seeds(s, d):
    """Partitions of the users of each micro-batch, on the graph of all events so far; a user's latest one stays."""
    from localcomm import sources
    from localcomm.operators.partition import attributed_partition
    from localcomm.params import Params
    from localcomm.plans.stages import staged

    root = f"{shared_root(s)}/refresh-{uuid.uuid4().hex}"

    def touched(batch: DataFrame, number: int) -> None:
        batch.withColumn("ts", F.col("ts").cast("timestamp_ntz")).write.mode("overwrite").parquet(f"{root}/seen/events.parquet/batch={number}")
        g = sources.users(batch.sparkSession, f"{root}/seen")
        seeds = staged(batch.select(F.col("user_id").alias("seed")).where("seed IS NOT NULL").distinct(), "touched")
        found = attributed_partition(staged(g.combined(), "so-far"), seeds, g.nodes.count(), Params(stop="fixed"))
        found.summary.withColumn("batch", F.lit(number)).write.mode("append").parquet(f"{root}/out")

    q = source(s, d).writeStream.foreachBatch(touched).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    latest = F.max_by(F.struct("size", "score", "target_met"), "batch").alias("r")
    return s.read.parquet(f"{root}/out").groupBy("seed").agg(latest).select("seed", "r.size", F.round("r.score", 6).alias("score"), "r.target_met")


def queries():
    # A window is out once the watermark, ten minutes behind the latest event, has passed its end.
    closed = "(SELECT max(ts) FROM events) - INTERVAL 10 MINUTES"
    hour = "SELECT start, user_id, count(*) AS events FROM (SELECT {w} AS start, user_id FROM events{x}) WHERE start + INTERVAL 1 HOUR <= " + closed + " GROUP BY 1, 2"
    return [
        ("stream_tumbling", hour.format(w="time_bucket(INTERVAL 1 HOUR, ts)", x=""), tumbling),
        ("stream_sliding", hour.format(w="time_bucket(INTERVAL 30 MINUTES, ts) - INTERVAL 30 MINUTES * k", x=", range(2) AS r(k)"), sliding),
        (
            "stream_session",
            "SELECT min(ts) AS start, user_id, count(*) AS events FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTES <= " + closed,
            session,
        ),
        (
            "stream_late_drop",
            "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, user_id, count(*) AS events FROM events WHERE floor(epoch(ts)) >= (SELECT CAST(min(floor(epoch(ts))) AS BIGINT) + CAST(max(floor(epoch(ts))) AS BIGINT) FROM events) // 2 GROUP BY 1, 2 HAVING time_bucket(INTERVAL 1 HOUR, min(ts)) + INTERVAL 1 HOUR <= " + closed,
            late_drop,
        ),
        ("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events", dedup),
        ("stream_static_join", "SELECT event_id, user_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id", static_join),
        ("stream_degree_state", "SELECT user_id, count(DISTINCT props) AS degree FROM events GROUP BY user_id", degree_state),
        ("stream_refresh_seeds", None, refresh_seeds),
    ]
