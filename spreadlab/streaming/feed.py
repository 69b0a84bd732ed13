"""Streaming feeder: purchases as weighted edges, windowed counts, and a watch list re-estimated per batch."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from spreadlab.storage import scratch_path

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, pattern: str = "events.parquet", files: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", files).parquet(folder)


def windowed_counts(events: DataFrame, width: str = "1 day", late: str = "10 minutes", slide: str | None = None) -> DataFrame:
    """(window, user_id, event_type, n, total) with a watermark; repeats of an event_id within it count once."""
    held = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return held.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(session, user_id, n)."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def successor_edges(events: DataFrame, kind: str = "purchase") -> DataFrame:
    """(src, dst) of successive users of one event type, with the last event as state."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        users = rows["user_id"].tolist()
        if state.exists:
            users = [state.get[0], *users]
        state.update((users[-1],))
        yield pd.DataFrame({"src": users[:-1], "dst": users[1:]})

    picked = events.filter(F.col("event_type") == kind)
    return picked.groupBy("event_type").applyInPandasWithState(step, "src long, dst long", "last long", "append", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is and return the sink's table."""
    spark = stream.sparkSession
    out, marks = scratch_path(spark, label), scratch_path(spark, f"{label}-marks")
    query = stream.writeStream.format("parquet").outputMode(mode).option("path", out).option("checkpointLocation", marks).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def watch(stream: DataFrame, on_edges, label: str = "watch"):
    """foreachBatch: hand each batch of edges to ``on_edges(batch, batch_id)``, e.g. to re-estimate a watch list."""
    return stream.writeStream.foreachBatch(on_edges).option("checkpointLocation", scratch_path(stream.sparkSession, f"{label}-marks")).trigger(availableNow=True).start()


def drain_complete(stream: DataFrame, label: str) -> DataFrame:
    """As drain for complete mode: each batch replaces the table."""
    spark = stream.sparkSession
    out, marks = scratch_path(spark, label), scratch_path(spark, f"{label}-marks")
    query = stream.writeStream.outputMode("complete").foreachBatch(lambda b, _: b.write.mode("overwrite").parquet(out)).option("checkpointLocation", marks).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)
