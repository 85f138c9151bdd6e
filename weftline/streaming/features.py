"""Event-time features as streams, and batches of specifications that arrive as files.

Event times are cast to session-zone timestamps, which watermarks need; window bounds
go back to timestamps without a zone.  Every query here runs what is available and ends.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..runtime.cache import shared_root


def event_stream(spark: SparkSession, sf_dir: str, files: int = 4) -> DataFrame:
    """Events by time as several files, read as a stream."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    path = f"{shared_root(spark)}/events-{uuid.uuid4().hex}"
    events.repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def run_available(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there into Parquet: appended, or for complete the last result, for update all updates."""
    spark, name = stream.sparkSession, f"weftline_{uuid.uuid4().hex}"
    base = f"{shared_root(spark)}/{name}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}-state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", base).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(base)

    def each(df: DataFrame, batch: int) -> None:
        # a batch that is run again overwrites its own folder
        df.write.mode("overwrite").parquet(base if mode == "complete" else f"{base}/batch={batch}")

    writer.foreachBatch(each).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(base)


def windows(stream: DataFrame, size: str, slide: str | None = None, lateness: str = "1 hour") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", lateness).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"))


def sessions(stream: DataFrame, gap: str, lateness: str = "3650 days") -> DataFrame:
    return stream.withWatermark("ts", lateness).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def bounds(df: DataFrame, *rest: str) -> DataFrame:
    return df.select(F.col("w.start").cast("timestamp_ntz").alias("window_start"), *rest)


def running_state(stream: DataFrame) -> DataFrame:
    """Per user the events and their value so far, kept as state between triggers."""

    def update(key: tuple, batches, state: GroupState):
        n, total = state.get if state.exists else (0, 0.0)
        for pdf in batches:
            n, total = n + len(pdf), total + float(pdf["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return stream.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, n bigint, total double", "n bigint, total double", "update", GroupStateTimeout.NoTimeout)


def stream_batches(spark: SparkSession, folder: str, handle: Callable[[list[str]], None]) -> None:
    """Specifications, one JSON a line, handled file by file as they come."""

    def each(df: DataFrame, _: int) -> None:
        handle([r["value"] for r in df.collect()])  # specifications are few and small

    stream = spark.readStream.schema("value string").option("maxFilesPerTrigger", 1).text(folder)
    stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{shared_root(spark)}/specs-{uuid.uuid4().hex}").trigger(availableNow=True).start().awaitTermination()
