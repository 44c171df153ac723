"""Query streams: event vectors searched in micro-batches, windows over answers, state per user.

Runs to the end of what is available and hands back the sink's table, so a batch caller can read
the result; a service would start the same plans with its own trigger and sink.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything the stream emits until its input ends."""
    name = "t" + uuid.uuid4().hex
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def tumbling(spark, sf_dir) -> DataFrame:
    d = event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return drained(d, "complete").select(F.unix_timestamp("w.start").alias("start"), "event_type", "n", "total")


def sliding(spark, sf_dir) -> DataFrame:
    d = event_stream(spark, sf_dir).groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return drained(d, "complete").select(F.unix_timestamp("w.start").alias("start"), "n")


def sessions(spark, sf_dir) -> DataFrame:
    d = event_stream(spark, sf_dir).groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(d, "complete").select("user_id", F.unix_timestamp("w.start").alias("start"), "n")


def deduplicated(spark, sf_dir) -> DataFrame:
    d = event_stream(spark, sf_dir).withWatermark("ts", "365 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return drained(d).select("user_id", "event_type")


def static_join(spark, sf_dir) -> DataFrame:
    """Each event with its user's name, where the user is a customer."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", "c_name")
    return drained(event_stream(spark, sf_dir).join(c, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_name"))


def search_stream(stream: DataFrame, vectors: DataFrame, k: int, sink) -> None:
    """Each micro-batch of (qid, vec) queries searched against a static set; sink(answers, epoch) writes it."""
    from ..operators.neighbors import exact_knn

    q = stream.writeStream.foreachBatch(lambda df, epoch: sink(exact_knn(vectors, df, k), epoch)).trigger(availableNow=True).start()
    q.awaitTermination()


def insert_stream(stream: DataFrame, path: str) -> None:
    """New vectors appended to a delta shard; each epoch has its own directory, so a retry overwrites it."""

    def put(df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    q = stream.writeStream.foreachBatch(put).trigger(availableNow=True).start()
    q.awaitTermination()
