"""Streams of events: windows, late data, joins, dedup, stateful placement and running measures.

Each query replays the events table through Structured Streaming into a table in the shared folder and
returns what the stream has produced, so that it can be compared with a batch query.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from hgpart.plans.checkpoints import shared_folder

QUERIES: dict = {}
ORACLE: dict = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return register


def replay(spark: SparkSession, sf_dir: str, files: int = 4, shuffled: bool = False) -> DataFrame:
    """The events as a file stream in `files` batches, by time or dealt at random."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    path = f"{shared_folder(spark)}/events-{uuid.uuid4().hex}"
    (events.repartition(files, "event_id") if shuffled else events.repartitionByRange(files, "ts")).write.parquet(path)
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that the stream gives until its source is empty, from files in the shared folder: appended ones by the file sink,
    complete ones rewritten by each micro-batch."""
    spark = stream.sparkSession
    at = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{at}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{at}/data").outputMode("append").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/data")
    done = [-1]

    def whole(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/data/{number}")  # rewritten whole on a retry
        done[0] = number

    writer.foreachBatch(whole).outputMode(mode).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/data/{done[0]}") if done[0] >= 0 else spark.createDataFrame([], stream.schema)


@query("stream_tumbling", "SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, count(*) AS n_events FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    return drained(replay(spark, d).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n_events")), "complete").select(F.col("w.start").alias("start"), "event_type", "n_events")


@query("stream_sliding", "SELECT (date_trunc('day', ts) + k * INTERVAL 12 HOUR)::TIMESTAMP AS start, count(*) AS n_events FROM events, (VALUES (-1), (0), (1)) t(k) WHERE ts >= date_trunc('day', ts) + k * INTERVAL 12 HOUR AND ts < date_trunc('day', ts) + (k + 2) * INTERVAL 12 HOUR GROUP BY 1")
def stream_sliding(spark, d):
    return drained(replay(spark, d).groupBy(F.window("ts", "1 day", "12 hours").alias("w")).agg(F.count(F.lit(1)).alias("n_events")), "complete").select(F.col("w.start").alias("start"), "n_events")


@query("stream_session", "SELECT user_id, min(ts)::TIMESTAMP AS start, count(*) AS n_events FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, (coalesce(date_diff('microsecond', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts) >= 21600000000, true))::INT AS new FROM events)) GROUP BY user_id, s")
def stream_session(spark, d):
    sessions = replay(spark, d).groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n_events"))
    return drained(sessions, "complete").select("user_id", F.col("w.start").alias("start"), "n_events")


@query("stream_late")
def stream_late(spark, d):
    """With the events dealt at random, those more than an hour behind the newest are dropped."""
    counted = replay(spark, d, shuffled=True).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n_events"))
    return drained(counted).select(F.col("w.start").alias("start"), "n_events")


@query("stream_join_static", "SELECT event_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey")
def stream_join_static(spark, d):
    return drained(replay(spark, d).join(spark.read.parquet(f"{d}/customer.parquet"), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_nationkey"))


@query("stream_join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_join_interval(spark, d):
    a = replay(spark, d).select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t1")).withWatermark("t1", "40 days")
    b = replay(spark, d).select(F.col("event_id").alias("b"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "40 days")
    return drained(a.join(b, F.expr("user_id = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL 1 HOUR")).select("a", "b"))


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, d):
    return drained(replay(spark, d).select("user_id", "event_type", "ts").withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type"))


@query("stream_one_pass")
def stream_one_pass(spark, d, most: int = 8, shards: int = 4):
    """One-pass filling of users as they first appear, by shard. A first stream lets each user through once, its state spread over
    users; a second one fills partitions, its state being the open partition of each shard and how full it is."""

    def place(key, batches, state: GroupState):
        shard = int(key[0])
        n_open, size = state.get if state.exists else (0, 0)
        out = []
        for _, u in sorted({(t, u) for pdf in batches for t, u in zip(pdf["ts"], pdf["user_id"])}):
            if size == most:
                n_open, size = n_open + 1, 0
            size += 1
            out.append((shard, int(u), shard + shards * n_open))
        state.update((n_open, size))
        yield pd.DataFrame(out, columns=["shard", "n", "p"])

    first = drained(replay(spark, d).select("user_id", "ts").withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id"]))
    keyed = spark.readStream.schema(first.schema).parquet(first.inputFiles()[0].rsplit("/", 1)[0]).select(F.expr(f"user_id % {shards}").alias("shard"), "user_id", "ts")
    placed = keyed.groupBy("shard").applyInPandasWithState(place, "shard long, n long, p long", "n_open long, size long", "append", GroupStateTimeout.NoTimeout)
    return drained(placed).select("n", "p")


@query("stream_connectivity", "SELECT sum(parts - 1)::BIGINT AS connectivity FROM (SELECT date_trunc('hour', ts), event_type, count(DISTINCT user_id % 8) AS parts FROM events GROUP BY 1, 2)")
def stream_connectivity(spark, d, parts: int = 8):
    """Connectivity of the users' hourly hyperedges under user_id % parts, merged batch by batch: each
    micro-batch adds its distinct (hyperedge, partition) pairs to a written table."""
    at = f"{shared_folder(spark)}/pairs-{uuid.uuid4().hex}"
    pairs = replay(spark, d).select(F.date_trunc("hour", "ts").alias("hour"), "event_type", F.expr(f"user_id % {parts}").alias("p"))

    def merge(batch: DataFrame, number: int) -> None:
        batch.distinct().write.mode("overwrite").parquet(f"{at}/batch={number}")  # rewritten whole on a retry

    q = pairs.writeStream.foreachBatch(merge).option("checkpointLocation", f"{at}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    spans = spark.read.parquet(at).select("hour", "event_type", "p").distinct().groupBy("hour", "event_type").agg(F.count(F.lit(1)).alias("parts"))
    return spans.agg(F.sum(F.col("parts") - 1).alias("connectivity"))
