"""Payloads in content-defined chunks, stored once each.

A payload of 8-bit samples is cut where a rolling gear hash of its last 32 bytes has CUT_BITS zero bits. A medium is
the ordered list of its chunks' digests. Chunks that occur once in the corpus lie beside their medium's list, in order;
chunks that occur again lie in a store, once, which Spark joins fill and read. What is stored of a chunk, at either place,
is a record of length, digest and samples, and of a medium a header; the stored form of a medium is its header and the
records of its chunks in order, as they are read. Each is checked against its digest, and gives the payload's samples.

A null text is the empty payload; payloads are padded with zero bytes to a positive multiple of 64. Equal payloads are
one medium. Rows that repeat an id are rows of their own.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sieve import passes, sieve_of
from .storage import scratch, send
from .textkernel import lean, mix, text_batches

BLOCK = 64
LEAST, MOST, CUT_BITS = 256, 16_384, 10
MAGIC = b"EBMEDIA2"
#: Header of a medium: magic, payload bytes, chunks. Head of a chunk's record: length, digest.
HEADER, RECORD = "<8sQI", "<I32s"
#: One value for each byte, from a rule.
GEAR = (mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) & np.uint64(0xFFFFFFFF)).astype(np.uint32)


def payload_of(text: bytes | None) -> bytes:
    text = text or b""
    return text + bytes(max(1, -(-len(text) // BLOCK)) * BLOCK - len(text))


def cuts(payload: bytes) -> list[int]:
    """Where chunks end: after the first place that is LEAST on and whose gear hash says so, and MOST on at most."""
    h = GEAR[np.frombuffer(payload, dtype=np.uint8)]
    for step in (1, 2, 4, 8, 16):  # sums of the last 2, 4, ... 32 values, each shifted by its distance
        older = h[:-step] << np.uint32(step)
        h[step:] = h[step:] + older
    marks = (np.flatnonzero(h >> np.uint32(32 - CUT_BITS) == 0) + 1).tolist()
    out, start = [], 0
    for m in [*marks, len(payload)]:
        while m - start > MOST:
            start += MOST
            out.append(start)
        if m - start >= LEAST or (m == len(payload) and m > start):
            start = m
            out.append(m)
    return out


def chunks_of(payload: bytes) -> list[bytes]:
    ends = cuts(payload)
    return [payload[a:b] for a, b in zip([0, *ends[:-1]], ends)]


def feature_of(payload: bytes, n_chunks: int) -> str:
    x = np.frombuffer(payload, dtype=np.uint8).astype(np.int64) - 128
    crossings = int(np.count_nonzero((x[1:] >= 0) != (x[:-1] >= 0)))
    return f"chunks={n_chunks};mean={x.mean():.4f};rms={np.sqrt((x * x).mean()):.4f};crossings={crossings};peak={int(np.abs(x).max())}"


def record_of(digest: bytes, samples: bytes) -> bytes:
    return struct.pack(RECORD, len(samples), digest) + samples


def read_back(header: bytes, records: list[bytes]) -> tuple[int, str, int, int, str, str]:
    """payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, feature of a medium as stored."""
    parts = []
    for record in records:
        length, digest = struct.unpack_from(RECORD, record)
        parts.append(record[struct.calcsize(RECORD) :])
        if len(parts[-1]) != length or hashlib.sha256(parts[-1]).digest() != digest:
            raise ValueError("a stored chunk does not match its digest")
    payload, form = b"".join(parts), b"".join([header, *records])
    if struct.unpack(HEADER, header) != (MAGIC, len(payload), len(records)):
        raise ValueError("a stored medium does not match its header")
    return len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-BLOCK:]), len(form), hashlib.sha256(form).hexdigest(), feature_of(payload, len(parts))


VALUES = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
ROWS = "kind int, key {}, n_bytes long, medium binary, recipe binary, samples binary, digest binary"


def entries(recipe: bytes) -> tuple[bytes, list[bytes | None]]:
    """A medium's header, and the digest of each chunk that is in the store; None for one that lies beside the list."""
    at, out = struct.calcsize(HEADER), []
    while at < len(recipe):
        out.append(recipe[at + 1 : at + 33] if recipe[at] else None)
        at += 33 if recipe[at] else 1
    return recipe[: struct.calcsize(HEADER)], out


def together(listed: list[bytes | None], own: bytes, there: dict[bytes, bytes]) -> list[bytes]:
    """The records of a medium in order: its own ones, one after another, and those of the store."""
    records, at = [], 0
    for digest in listed:
        if digest is None:
            end = at + struct.calcsize(RECORD) + struct.unpack_from("<I", own, at)[0]
            records.append(own[at:end])
            at = end
        else:
            records.append(there[digest])
    return records


def store(docs: DataFrame, key: str = "doc_id", text: str = "text") -> str:
    """Write documents (kind 0), media (1) and chunks of the store (2) to the shared folder; gives the path."""
    spark = docs.sparkSession
    rows = docs.select(F.col(key).alias("key"), F.col(text).alias("text"))
    kind = dict(rows.dtypes)["key"]

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, texts in text_batches(batches):
            yield pa.RecordBatch.from_arrays([pa.array([hashlib.sha256(c).digest() for t in texts for c in chunks_of(payload_of(t))], pa.binary())], ["digest"])

    again = rows.select("text").mapInArrow(lean(digests), "digest binary").groupBy("digest").count().where("count > 1")
    first = F.conv(F.hex(F.substring("digest", 2, 7)), 16, 10).cast("long")  # seven bytes fit a BIGINT
    sieve = send(spark, sieve_of(again.select(first.alias("short"))))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        media: set[bytes] = set()
        sent: set[bytes] = set()
        for batch, texts in text_batches(batches):
            out: list[tuple] = []
            for k, t in zip(batch.column(0).to_pylist(), texts):
                parts = chunks_of(payload_of(t))
                names = [hashlib.sha256(c).digest() for c in parts]
                shared = passes(sieve.value, np.array([int.from_bytes(d[1:8], "big") for d in names], dtype=np.int64)).tolist()
                recipe = struct.pack(HEADER, MAGIC, sum(map(len, parts)), len(parts)) + b"".join(b"\1" + d if s else b"\0" for d, s in zip(names, shared))
                medium = hashlib.sha256(b"".join(names)).digest()
                out.append((0, k, len(t or b""), medium, None, None, None))
                if medium not in media:
                    if all(shared):  # only such a medium can come again
                        media.add(medium)
                    out.append((1, None, None, medium, recipe, b"".join(record_of(d, c) for d, c, s in zip(names, parts, shared) if not s), None))
                for d, c, s in zip(names, parts, shared):
                    if s and d not in sent:
                        sent.add(d)
                        out.append((2, None, None, None, None, record_of(d, c), d))
            kinds = [pa.int32(), batch.column(0).type, pa.int64(), *[pa.binary()] * 4]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], ["kind", "key", "n_bytes", "medium", "recipe", "samples", "digest"])

    path = scratch(spark, "media")
    dealt = rows.mapInArrow(lean(deal), ROWS.format(kind))
    dealt.write.partitionBy("kind").option("compression", "zstd").parquet(f"{path}/dealt")
    spark.read.schema(dealt.schema).parquet(f"{path}/dealt").where("kind = 2").groupBy("digest").agg(F.first("samples").alias("samples")).write.option("compression", "zstd").parquet(f"{path}/store")
    return path


def fetch(docs: DataFrame, path: str, key: str = "doc_id") -> DataFrame:
    """key, n_bytes and VALUES of every document, from what store() has written. docs gives the key's type."""
    spark = docs.sparkSession
    dealt = spark.read.schema(ROWS.format(dict(docs.dtypes)[key])).parquet(f"{path}/dealt")
    chunks = spark.read.schema("digest binary, samples binary").parquet(f"{path}/store")
    names = [x.split()[0] for x in VALUES.split(", ")]

    def sort_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Media without chunks in the store are read at once; of the others come the list and each stored digest."""
        kinds = [pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary(), pa.binary(), pa.binary()]
        for batch in batches:
            out: list[tuple] = []
            for medium, recipe, samples in zip(*(batch.column(i).to_pylist() for i in range(3))):
                header, listed = entries(recipe)
                wanted = {d for d in listed if d is not None}
                if wanted:
                    out.append((medium, *[None] * 6, recipe, samples, None))
                    out.extend((medium, *[None] * 8, d) for d in wanted)
                else:
                    out.append((medium, *read_back(header, together(listed, samples, {})), None, None, None))
                if len(out) > 2000:
                    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], ["medium", *names, "recipe", "samples", "digest"])
                    out = []
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], ["medium", *names, "recipe", "samples", "digest"])

    def put_together(frame: pd.DataFrame) -> pd.DataFrame:
        lists = frame[frame["recipe"].notna()].iloc[0]
        there = {d: s for d, s in zip(frame["digest"], frame["samples"]) if d is not None}
        header, listed = entries(lists["recipe"])
        return pd.DataFrame([(lists["medium"], *read_back(header, together(listed, lists["samples"], there)))], columns=["medium", *names])

    media = dealt.where("kind = 1").select("medium", "recipe", "samples")
    lone = media.where("length(samples) > 0").unionByName(media.where("length(samples) = 0").dropDuplicates(["medium"]))
    sorted_out = lone.mapInArrow(lean(sort_out), f"medium binary, {VALUES}, recipe binary, samples binary, digest binary")
    done = sorted_out.where("payload_bytes IS NOT NULL").select("medium", *names)
    open_lists = sorted_out.where("recipe IS NOT NULL").select("medium", "recipe", "samples", "digest")
    found = sorted_out.where("digest IS NOT NULL").select("medium", "digest").join(chunks, "digest").select("medium", F.lit(None).cast("binary").alias("recipe"), "samples", "digest")
    joined = open_lists.unionByName(found).groupBy("medium").applyInPandas(put_together, f"medium binary, {VALUES}")
    return dealt.where("kind = 0").select(F.col("key").alias(key), "n_bytes", "medium").join(done.unionByName(joined), "medium").drop("medium")
