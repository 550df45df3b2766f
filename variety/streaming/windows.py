"""Windowed, deduplicated and stateful statistics over an event stream."""

from __future__ import annotations

import math
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import SCHEMAS


def events(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", per_trigger).parquet(f"{sf_dir}/events.parquet*")


def stamped(df: DataFrame) -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(df: DataFrame, width: str = "1 hour") -> DataFrame:
    return df.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(df: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return df.groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(df: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return df.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(df: DataFrame, within: bool = False) -> DataFrame:
    """One row an event_id. ``within`` a watermark old ids are forgotten and late rows are lost; without it every id is kept."""
    return df.dropDuplicatesWithinWatermark(["event_id"]) if within and df.isStreaming else df.dropDuplicates(["event_id"])


def encoding_statistics(df: DataFrame) -> DataFrame:
    """Running count and mean of each category, to be blended like a target encoding."""
    return df.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean_value"))


def with_frozen_encodings(df: DataFrame, encodings: DataFrame) -> DataFrame:
    """Stream rows beside encodings frozen at training; categories unseen there keep nulls. Spark broadcasts the small side by its size."""
    return df.join(encodings, "event_type", "left")


def followed_within(df: DataFrame, first: str, then: str, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Pairs of a user's events of two types, the second at most ``within`` after the first. Watermarks on both sides bound the state."""
    a = df.where(F.col("event_type") == first).select(F.col("user_id"), F.col("event_id").alias("first_id"), F.col("ts").alias("first_ts"))
    b = df.where(F.col("event_type") == then).select(F.col("user_id").alias("then_user"), F.col("event_id").alias("then_id"), F.col("ts").alias("then_ts"))
    if df.isStreaming:
        a, b = a.withWatermark("first_ts", late), b.withWatermark("then_ts", late)
    return a.join(b, F.expr(f"user_id = then_user AND then_ts >= first_ts AND then_ts <= first_ts + INTERVAL {within}")).select("user_id", "first_id", "then_id")


def smoothed(df: DataFrame, prior: float, k_min: float = 20.0, f: float = 10.0) -> DataFrame:
    """Each user's running mean, drawn to ``prior`` while its count is small; the state is a count and a sum, updated batch by batch."""

    def step(key, frames, state):
        n, total = state.get if state.exists else (0, 0.0)
        for x in frames:
            values = x["value"].dropna()
            n, total = n + len(values), total + float(values.sum())
        state.update((n, total))
        trust = 1.0 / (1.0 + math.exp(min(-(n - k_min) / f, 700.0)))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "encoding": [trust * total / n + (1 - trust) * prior if n else prior]})

    return df.select("user_id", "value").groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, encoding double", "n long, total double", "update", "NoTimeout")


#: State is on local disk; that of the default provider is in the heap, one map a version.
ON_DISK = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def run_once(stream: DataFrame, name: str, checkpoint: str, mode: str = "complete", each: Callable | None = None) -> DataFrame | None:
    """All that is there now, then stop. The rows come back: appended ones from files under ``checkpoint``,
    others, a row a group and batch, from the memory table ``name``. With ``each(batch, id)`` they go there instead."""
    spark, rows = stream.sparkSession, f"{checkpoint}/rows"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if each:
        writer = writer.foreachBatch(each)
    elif mode == "append":
        writer = writer.format("parquet").option("path", rows)
    else:
        writer = writer.format("memory").queryName(name)
    plain = spark.conf.get(ON_DISK[0], None)
    spark.conf.set(*ON_DISK)
    try:
        query = writer.start()
    finally:
        spark.conf.set(ON_DISK[0], plain) if plain else spark.conf.unset(ON_DISK[0])
    query.awaitTermination()
    if each:
        return None
    return spark.read.schema(stream.schema).parquet(rows) if mode == "append" else spark.table(name)
