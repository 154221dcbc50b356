"""Shards by jump consistent hashing: a stable key and the number of shards decide, no ring table is kept,
and one shard more takes keys only into itself.

Rows with equal keys share a shard. A null text has no bytes and the checksum of the empty text; a null key is
placed as key 0 and sorts first. Tables may be empty and may have further columns, which are not read.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Rows of one cell, the unit in which slots are numbered; the cells of a shard are added up.
CELL_ROWS = 2048
#: Bytes that a row takes besides its text.
ROW_OVERHEAD = 16

#: Fixed values of the published generator.
_STEP, _ONE = np.uint64(2862933555777941757), np.uint64(1)


def jump_hash(keys: np.ndarray, shards: int) -> np.ndarray:
    """The shard, from 0, of each unsigned 64-bit key."""
    state = keys.astype(np.uint64)
    at = np.zeros(len(state), dtype=np.int64)
    live, ahead = np.arange(len(state)), np.zeros(len(state))
    while len(live):
        at[live] = ahead.astype(np.int64)
        state[live] = state[live] * _STEP + _ONE
        draw = (state[live] >> np.uint64(33)).astype(np.float64) + 1.0
        ahead = np.floor((at[live] + 1) * (float(1 << 31) / draw))
        on = ahead < shards
        live, ahead = live[on], ahead[on]
    return at.astype(np.int32)


def shard_column(key, shards: int):
    """A column of jump_hash over a BIGINT key column."""

    @F.pandas_udf("int")
    def place(keys: pd.Series) -> pd.Series:
        return pd.Series(jump_hash(keys.fillna(0).to_numpy(dtype=np.int64).view(np.uint64), shards))

    return place(key)


def assign_shards(df: DataFrame, shards: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, size, text_crc32, law, shard, slot, grown_shard.

    Slots are gapless from 0 in each shard. Rows are dealt into cells by a hash of their key, numbered inside a
    cell, and a cell begins where the smaller cells of its shard end: no task sees a whole shard.
    """
    total = df.count()
    cells = max(1, math.ceil(total / (shards * CELL_ROWS)))
    raw = F.coalesce(F.col(text), F.lit(""))
    rows = df.select(
        F.col(key).cast("long").alias("doc_id"),
        (F.octet_length(raw) + F.lit(ROW_OVERHEAD)).cast("long").alias("size"),
        F.crc32(raw.cast("binary")).alias("text_crc32"),
    )
    keys = lambda d: d.withColumn("shard", shard_column(F.col("doc_id"), shards)).withColumn("cell", F.pmod(F.xxhash64(F.coalesce("doc_id", F.lit(0))), F.lit(cells)))
    filled = keys(df.select(F.col(key).cast("long").alias("doc_id"))).groupBy("shard", "cell").count()
    begins = filled.select("shard", "cell", (F.sum("count").over(Window.partitionBy("shard").orderBy("cell")) - F.col("count")).alias("begin"))
    inside = Window.partitionBy("shard", "cell").orderBy("doc_id", "text_crc32", "size")
    return (
        keys(rows).withColumn("grown_shard", shard_column(F.col("doc_id"), shards + 1))
        .withColumn("place", F.row_number().over(inside) - 1)
        .join(begins, ["shard", "cell"])
        .select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", (F.col("begin") + F.col("place")).cast("long").alias("slot"), "grown_shard")
    )
