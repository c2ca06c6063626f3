"""Streams over the events table as queries: each runs over all there is and returns what it wrote.

A result that grows with the events goes to files, sessions too; windows of fixed places, which are few, go to a table in memory."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from keyless import codecs, store as S, streaming
from keyless.shared import scratch
from keyless.workloads import query, read

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(SCHEMA).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events*.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def to_files(spark, stream: DataFrame, name: str) -> DataFrame:
    """Append to files until the source is used up; the files."""
    path = scratch(spark, name)
    stream.writeStream.format("parquet").option("checkpointLocation", f"{path}-state").outputMode("append").trigger(availableNow=True).start(f"{path}-out").awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}-out")


def to_table(spark, stream: DataFrame) -> DataFrame:
    """All windows, from a table in memory."""
    name = f"keyless_{uuid.uuid4().hex[:12]}"
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", scratch(spark, name)).outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def to_last_files(spark, stream: DataFrame, name: str) -> DataFrame:
    """All rows of the result after the last batch, each batch written by the executors."""
    path, done = scratch(spark, name), []

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}-out/{epoch}")
        done.append(epoch)

    stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}-state").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}-out/{done[-1]}") if done else spark.createDataFrame([], stream.schema)


@query("SELECT event_id, event_type AS v FROM events")
def stream_lookup(spark, sf_dir):
    """A stream probes a store that was built before."""
    df = read(spark, sf_dir, "events", "event_id", "event_type")
    c = codecs.dictionary(df, "event_type")
    st = S.build(df, ["event_id"], c.encode(F.col("event_type")), S.Plan(width=c.width))
    st.decode = c.decode
    return to_files(spark, streaming.probe(events(spark, sf_dir).select("event_id"), st, out="v"), "stream-lookup")


_DAY = "strftime(to_timestamp(floor(epoch(ts) / {0}) * {0}) AT TIME ZONE 'UTC', '%Y-%m-%d %H:%M:%S')"


def shown() -> Column:
    return F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start")


@query(f"SELECT {_DAY.format(86400)} AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def stream_tumble(spark, sf_dir):
    return to_table(spark, streaming.tumbling(events(spark, sf_dir), "ts", "1 day", "1 day", "event_type")).select(shown(), "event_type", "n")


@query("SELECT strftime(to_timestamp((floor(epoch(ts) / 43200) - k) * 43200) AT TIME ZONE 'UTC', '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n FROM events, range(0, 2) r(k) GROUP BY 1")
def stream_slide(spark, sf_dir):
    return to_table(spark, streaming.sliding(events(spark, sf_dir), "ts", "1 day", "12 hours", "1 day")).select(shown(), "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, count(*)::BIGINT AS n FROM s GROUP BY user_id, k")
def stream_session(spark, sf_dir):
    return to_last_files(spark, streaming.sessions(events(spark, sf_dir), "ts", "6 hours", "1 day", "user_id"), "stream-session").select("user_id", "n")


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'click'")
def stream_join(spark, sf_dir):
    """Clicks within an hour of a view, both as streams."""
    ev = events(spark, sf_dir)
    a = ev.filter("event_type = 'view'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("first"))
    b = ev.filter("event_type = 'click'").select("user_id", F.col("ts").alias("then"), F.col("event_id").alias("second"))
    return to_files(spark, streaming.interval_join(a, b, "user_id", "at", "then", "1 hour", "3650 days"), "stream-join").select("first", "second")


@query("SELECT count(*)::BIGINT AS n, 0::BIGINT AS apart FROM events")
def stream_epoch(spark, sf_dir):
    """A batch of the stream rebuilds the store under a new epoch; the last one answers for all events."""
    from keyless import shelf

    path = scratch(spark, "stream-epoch")
    publish = lambda st, epoch: shelf.write(st, path, epoch)
    build = streaming.epochs(["event_id"], F.col("event_id") % 16, S.Plan(width=4), publish)
    events(spark, sf_dir).select("event_id").writeStream.foreachBatch(build).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start().awaitTermination()
    got = S.lookup(read(spark, sf_dir, "events", "event_id"), shelf.read(spark, path), out="v")
    return got.agg(F.count("*").alias("n"), F.count_if(F.col("v") != F.col("event_id") % 16).alias("apart"))


@query("SELECT event_id, CASE WHEN event_id % 5 = 0 THEN 99 ELSE event_id % 16 END::BIGINT AS v FROM events")
def stream_overlay(spark, sf_dir):
    """Keys that changed since the epoch, taken from a stream, win over the store."""
    df = read(spark, sf_dir, "events", "event_id")
    st = S.build(df, ["event_id"], F.col("event_id") % 16, S.Plan(width=4))
    changed = to_files(spark, events(spark, sf_dir).filter("event_id % 5 = 0").select("event_id", F.lit(99).cast("bigint").alias("v")), "stream-overlay")
    return streaming.overlay(S.lookup(df, st, out="v"), changed, "event_id", "v")
