"""Fixed-size Bloom filters, built by the executors: a bounded broadcast whatever the input. A filter only spares
shuffles, as what it lets through is joined exactly afterwards; when full it lets everything through."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .textkernel import mix

BITS = 23


def places(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    h = mix(keys.astype(np.int64).view(np.uint64) + np.uint64(0x9E3779B97F4A7C15))
    return (h >> np.uint64(64 - BITS)).astype(np.int64), (h & np.uint64((1 << BITS) - 1)).astype(np.int64)


def sieve_of(keys: DataFrame) -> np.ndarray:
    """The filter of a frame's one BIGINT column."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.zeros(1 << BITS, dtype=bool)
        some = False
        for batch in batches:
            for at in places(batch.column(0).to_numpy(zero_copy_only=False)):
                bits[at] = True
            some |= batch.num_rows > 0
        if some:
            yield pa.RecordBatch.from_arrays([pa.array([np.packbits(bits).tobytes()], pa.binary())], ["bits"])

    name = keys.columns[0]
    out = np.zeros((1 << BITS) // 8, dtype=np.uint8)
    for row in keys.where(f"{name} IS NOT NULL").coalesce(8).mapInArrow(run, "bits binary").toLocalIterator():
        out |= np.frombuffer(row[0], dtype=np.uint8)
    return out


def passes(sieve: np.ndarray, keys: np.ndarray) -> np.ndarray:
    ok = np.ones(len(keys), dtype=bool)
    for at in places(keys):
        ok &= (sieve[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1).astype(bool)
    return ok
