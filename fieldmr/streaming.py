"""Snapshots from streams: windows of events become grid cells, and each batch goes through the batch codecs."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from .fields import cents
from .schema import EVENTS
from .tables import shared_dir


def scratch(spark: SparkSession, label: str) -> str:
    """A folder for checkpoints and sinks, in the place all executors share."""
    return f"{shared_dir(spark)}/fieldmr-{label}-{uuid.uuid4().hex}"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events file as a stream with an explicit schema."""
    return spark.readStream.schema(EVENTS.replace("ts timestamp", "ts timestamp_ntz")).parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """All rows that a stream emits until its source is exhausted, as a table."""
    spark = stream.sparkSession
    if mode == "append":
        out = scratch(spark, label)
        q = stream.writeStream.format("parquet").option("checkpointLocation", scratch(spark, f"{label}-state")).outputMode("append").trigger(availableNow=True).start(out)
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    # a complete result replaces the one before, an update adds to it
    out = scratch(spark, label)

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={number}")

    stream.writeStream.foreachBatch(write).option("checkpointLocation", scratch(spark, f"{label}-state")).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out).select(*stream.columns)


def tumbling(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Snapshot cells: value in cents and count per window, user bucket and type."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), (F.col("user_id") % 16).cast("int").alias("x"), "event_type").agg(F.sum(cents("value")).alias("v"), F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("start"), "x", "event_type", "v", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("w.start").alias("start"), F.unix_timestamp("w.end").alias("end"), "n")


def with_types(events: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Stream-static join: the dictionary of types is a few rows."""
    return events.join(F.broadcast(dictionary), "event_type")


def pairs_within(events: DataFrame, first: str, then: str, width: str = "1 hour") -> DataFrame:
    """Stream-stream join: a user's first event of one kind and later ones of another within a time bound."""
    a = events.where(F.col("event_type") == first).select("event_id", "user_id", "ts").withWatermark("ts", width)
    b = events.where(F.col("event_type") == then).select(F.col("event_id").alias("next_id"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", width)
    near = (F.col("user_id") == F.col("u")) & (F.col("t") >= F.col("ts")) & (F.col("t") <= F.col("ts") + F.expr(f"INTERVAL {width}"))
    return a.join(b, near).select("event_id", "next_id", "user_id")


MODEL = "event_type string, n long, total long, square double"


def running_model(events: DataFrame) -> DataFrame:
    """State per type: count, sum and square sum of the values, carried from batch to batch."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total, square = state.get if state.exists else (0, 0, 0.0)
        for p in batches:
            c = (p["value"] * 100 + 0.5).astype("int64")
            n, total, square = n + len(c), total + int(c.sum()), square + float((c.astype("float64") ** 2).sum())
        state.update((n, total, square))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "total": [total], "square": [square]})

    return events.select("event_type", "value").groupBy("event_type").applyInPandasWithState(update, MODEL, "n long, total long, square double", "update", GroupStateTimeout.NoTimeout)


def compress_batches(stream: DataFrame, sink: str, encode: Callable[[DataFrame], DataFrame]) -> None:
    """Each micro-batch is encoded and written under its batch number, so a repeated batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        encode(batch).write.mode("overwrite").option("compression", "none").parquet(f"{sink}/batch={number}")

    q = stream.writeStream.foreachBatch(write).option("checkpointLocation", scratch(stream.sparkSession, "foreach")).trigger(availableNow=True).start()
    q.awaitTermination()
