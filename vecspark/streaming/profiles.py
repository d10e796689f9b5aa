"""Event streams to windowed profiles, deduplicated events, encoded appends and running state."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream, with event time as a zoned timestamp."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # A file stream wants a folder or a glob.
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 4).parquet(f"{path}*").withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    s = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "30 days") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_static(events: DataFrame, static: DataFrame, key: str) -> DataFrame:
    return events.join(F.broadcast(static), key)


def paired(left: DataFrame, right: DataFrame, late: str = "1 hour", within: str = "1 hour") -> DataFrame:
    """Events of one user within an interval after another: (a, b) ids."""
    x = left.withWatermark("ts", late).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta"))
    y = right.withWatermark("ts", late).select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("tb"))
    return x.join(y, (F.col("u") == F.col("v")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"interval {within}"))).select("a", "b")


def running_profiles(events: DataFrame) -> DataFrame:
    """Stateful counts by user: each batch emits the totals so far of the users it touched."""

    def step(key, frames, state):
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].fillna(0).sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream over everything available into a memory table."""
    name = f"drained_{uuid.uuid4().hex[:10]}"
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def append_codes(stream: DataFrame, encode, path: str, checkpoint: str):
    """foreachBatch sink: each micro-batch of vectors is encoded and appended to the index's files."""

    def write(batch: DataFrame, _: int) -> None:
        encode(batch).write.mode("append").parquet(path)

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
