"""Structured Streaming counterparts: loads by window, sessions, late rows, micro-batch packing, open bins as state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.packing import pack_balanced

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """Events as they arrive as files, with a timestamp that a watermark can stand on."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def with_lateness(df: DataFrame, delay: str = "12 hours") -> DataFrame:
    return df.withWatermark("ts", delay)


def stream_window_load(df: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    return df.groupBy(F.window("ts", size, slide or size).alias("w")).agg(F.count("*").alias("events")).select(F.unix_micros("w.start").alias("start"), "events")


def stream_sessions(df: DataFrame, gap: str = "6 hours") -> DataFrame:
    return df.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("size")).select("user_id", F.unix_micros("w.start").alias("start"), "size")


def stream_dedup(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.dropDuplicatesWithinWatermark(keys)


def stream_enrich(df: DataFrame, static: DataFrame, on: str) -> DataFrame:
    return df.join(static, on, "left")


def stream_pack(df: DataFrame, capacity: int, ranks: int, path: str, checkpoint: str) -> StreamingQuery:
    """Each micro-batch planned from its histogram, packed exactly by the batch operator and written with its batch id;
    written anew if the batch is retried. Larger items have bins of their own."""

    def pack(batch: DataFrame, number: int) -> None:
        got = pack_balanced(batch, capacity, ranks, oversize="isolate").assignment
        got.select("id", "size", "bin_id").write.mode("overwrite").parquet(f"{path}/batch={number}")

    return df.select("id", "size").writeStream.foreachBatch(pack).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stream_next_fit(df: DataFrame, key: str, capacity: int) -> DataFrame:
    """(key, id, size, bin_id): next fit for each key, whose state is the open bin's number and load."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        number, load = state.get if state.exists else (0, 0)
        rows = pd.concat(list(frames)).sort_values("id")
        bins = []
        for size in rows["size"]:
            if load + size > capacity:
                number, load = number + 1, 0
            load += size
            bins.append(number)
        state.update((int(number), int(load)))
        yield pd.DataFrame({key: [k[0]] * len(rows), "id": rows["id"].to_numpy(), "size": rows["size"].to_numpy(), "bin_id": bins})

    return df.select(key, "id", "size").groupBy(key).applyInPandasWithState(step, f"{key} long, id long, size long, bin_id long", "number long, load long", "append", GroupStateTimeout.NoTimeout)
