"""Graphs from streams of events: edges by window, running degrees, sessions, and placement against a fixed partition.

Rows that come after the watermark passed their window are dropped, and counted in the trace of `finished`.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphsplit.model import checkpoint_folder


def event_stream(spark: SparkSession, sf_dir: str, watermark: str = "40 days") -> DataFrame:
    """The events table as a stream, with a watermark on its time."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parque[t]").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def edge_windows(events: DataFrame, size: str = "1 day") -> DataFrame:
    """window, user_id, event_type, w: edges of the user and type graph in each window."""
    return events.groupBy(F.window("ts", size), "user_id", "event_type").agg(F.count("*").alias("w"))


def degrees(events: DataFrame) -> DataFrame:
    """user_id, degree, weight so far."""
    return events.groupBy("user_id").agg(F.size(F.collect_set("event_type")).cast("long").alias("degree"), F.count("*").alias("weight"))


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("events"))


def assign(events: DataFrame, anchor: Column, partition: DataFrame) -> DataFrame:
    """vid, block: every arriving event goes to the block of the vertex it hangs on. partition: anchor, block."""
    return events.select(F.col("event_id").alias("vid"), anchor.alias("anchor")).join(partition, "anchor").select("vid", "block")


def arrivals(events: DataFrame, anchor: Column, partition: DataFrame, size: str = "1 day") -> DataFrame:
    """window, user_id, block, w: each window's users go to the block that most of their events hang on, the smaller one of equals.

    partition: anchor, block. Counts by block are aggregated before the shuffle, so that a user with many events is no hot task.
    Output mode append: a window is placed once, when the watermark passes it.
    """
    hung = events.withColumn("anchor", anchor).join(partition, "anchor")
    counts = hung.groupBy(F.window("ts", size), "user_id", "block").agg(F.count("*").alias("w"))
    best = counts.groupBy("window", "user_id").agg(F.max(F.struct("w", (-F.col("block")).alias("b"))).alias("best"))
    return best.select("window", "user_id", (-F.col("best.b")).cast("int").alias("block"), F.col("best.w").alias("w"))


def finished(stream: DataFrame, mode: str, trace: dict | None = None) -> DataFrame:
    """All of a bounded stream's output, once it has read what there is; every batch is a table in the shared checkpoint folder.

    A batch that is run again replaces its own table. trace: gets the number of batches and of rows dropped as too late.
    """
    spark = stream.sparkSession
    at = f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}"
    done = []

    def sink(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/batch={number}")
        done.append(number)

    query = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", f"{at}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    if trace is not None:
        trace["batches"] = len(set(done))
        trace["late"] = sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])
    if not done:
        return spark.createDataFrame([], stream.schema)
    numbers = [max(done)] if mode == "complete" else sorted(set(done))
    return spark.read.schema(stream.schema).parquet(*[f"{at}/batch={k}" for k in numbers])
