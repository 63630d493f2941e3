"""Streams of graph changes: events as edges, with late data, windows, and a reservoir for each vertex."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubgraph.core.portable import uniform
from hubgraph.session import shared_dir


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """Events of the events.parquet of a folder as a stream with a watermark."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "events.parquet").parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")


def windowed_degree(events: DataFrame, width: str = "1 day") -> DataFrame:
    """(start, user_id, n, value): degree of each user in tumbling windows."""
    return events.groupBy(F.window("ts", width), "user_id").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("value")).select(F.col("window.start").alias("start"), "user_id", "n", "value")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def reservoir(events: DataFrame, size: int = 5, salt: str = "a") -> DataFrame:
    """Per user the `size` best scores u**(1/w) seen so far; equals the weighted sample of the batch."""
    scored = events.where("value > 0").select("user_id", "event_id", F.round(F.pow(uniform(salt, "user_id", "event_id"), 1 / F.col("value")), 9).alias("score"))

    def update(key, frames, state):
        held = list(state.get[0]) if state.exists else []
        held = [tuple(x) for x in zip(held[0::2], held[1::2], strict=True)]
        for f in frames:
            held += list(zip(f["score"].tolist(), f["event_id"].astype(float).tolist(), strict=True))
        held = sorted(held, key=lambda x: (-x[0], x[1]))[:size]
        state.update(([y for x in held for y in x],))
        yield pd.DataFrame({"user_id": key[0], "event_id": [int(e) for _, e in held], "score": [s for s, _ in held], "rank": range(1, len(held) + 1)})

    return scored.groupBy("user_id").applyInPandasWithState(update, "user_id long, event_id long, score double, rank int", "held array<double>", "update", "NoTimeout")


def run_to_table(stream: DataFrame, name: str, mode: str) -> DataFrame:
    """Run a stream over all that is there into a table: files of the shared folder where rows are only added, else (rows
    of an update replace others, which files can't) one in the driver's memory, which holds all updates."""
    spark = stream.sparkSession
    where = f"{shared_dir(spark)}/stream-{name}-{pd.Timestamp.now().value}"
    out = stream.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", where).trigger(availableNow=True)
    if mode == "append":
        out.format("parquet").start(f"{where}-rows").awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{where}-rows")
    out.format("memory").start().awaitTermination()
    return spark.table(name)
