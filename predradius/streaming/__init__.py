"""Streams over the events table: windows, deduplication and enrichment, drained with availableNow."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import shared_folder, table


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a file stream; ts carries a zone, which watermarks need."""
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(df: DataFrame, mode: str) -> DataFrame:
    """Runs a stream to its end and returns its sink: aggregates of bounded size."""
    name = f"sink_{uuid.uuid4().hex}"
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


@contextmanager
def disk_state(spark: SparkSession) -> Iterator[None]:
    """Streams that start inside keep their state in RocksDB, outside the heap; each takes its own copy of the settings at its start."""
    store = "spark.sql.streaming.stateStore."
    wanted = {f"{store}providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", f"{store}rocksdb.changelogCheckpointing.enabled": "true"}
    before = {key: spark.conf.get(key, None) for key in wanted}
    try:
        for key, value in wanted.items():
            spark.conf.set(key, value)
        yield
    finally:
        for key, value in before.items():
            if value is None:
                spark.conf.unset(key)
            else:
                spark.conf.set(key, value)


def stored(df: DataFrame) -> DataFrame:
    """Runs an appending stream to its end into files of the shared folder, written by the tasks: results that grow with the data."""
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    with disk_state(spark):
        query = df.writeStream.format("parquet").option("checkpointLocation", f"{folder}/state").outputMode("append").trigger(availableNow=True).start(f"{folder}/rows")
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{folder}/rows")


def closing(stream: DataFrame, delay: str) -> DataFrame:
    """The stream with a watermark on ts that passes all of its rows once it has been read, so that an appending query emits every window.

    A shadow of each row, a century later, moves the watermark and is dropped right behind it; the shadows never reach a shuffle.
    Rows without ts are in no window and are dropped too.
    """
    pair = F.array(F.struct("ts", F.col("ts").alias("own")), F.struct((F.col("ts") + F.expr("INTERVAL 100 YEAR")).alias("ts"), F.col("ts").alias("own")))
    marked = stream.withColumn("ts", F.explode(pair)).select(*(c for c in stream.columns if c != "ts"), "ts.ts", "ts.own").withWatermark("ts", delay)
    return marked.filter("ts = own").drop("own")  # it compares ts, so it is not pushed below the watermark


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drained(got.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n"), "complete")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = event_stream(spark, sf_dir).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return drained(got.select(F.unix_timestamp("window.start").alias("start"), "n"), "complete")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = closing(event_stream(spark, sf_dir), "1 hour").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return stored(got.select(F.unix_micros("session_window.start").alias("start"), "user_id", "n"))


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stored(event_stream(spark, sf_dir).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


def pass_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The running pass rate of a filter (value above 50) per event type."""
    got = event_stream(spark, sf_dir).groupBy("event_type").agg(F.count(F.lit(1)).alias("seen"), F.sum((F.col("value") > 50).cast("long")).alias("passed"))
    return drained(got, "complete")


def static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    got = event_stream(spark, sf_dir).withColumn("k", (F.col("user_id") % 25).cast("int")).join(F.broadcast(nation), F.col("k") == F.col("n_nationkey"))
    return drained(got.groupBy("n_name").agg(F.count(F.lit(1)).alias("n")), "complete")


def stream_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {"stream_tumbling": tumbling, "stream_sliding": sliding, "stream_session": session, "stream_dedup": dedup, "stream_pass_rate": pass_rate, "stream_static_join": static_join}


def stream_oracles() -> dict[str, str]:
    return {
        "stream_tumbling": "SELECT epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
        "stream_sliding": "SELECT start, count(*) AS n FROM (SELECT unnest([epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT, epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT - 3600]) AS start FROM events) GROUP BY ALL",
        "stream_session": "SELECT min(epoch_us(ts)) AS start, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s",
        "stream_dedup": "SELECT DISTINCT event_id FROM events",
        "stream_pass_rate": "SELECT event_type, count(*) AS seen, count(*) FILTER (WHERE value > 50) AS passed FROM events GROUP BY ALL",
        "stream_static_join": "SELECT n_name, count(*) AS n FROM events JOIN nation ON user_id % 25 = n_nationkey GROUP BY ALL",
    }
