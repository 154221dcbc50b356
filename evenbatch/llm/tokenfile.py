"""Token ids in binary segments with Elias-Fano coded document boundaries.

A segment holds the ids of consecutive documents one after another, 2 or 4 bytes an id, and where each document
ends: the ends never fall, so they are kept as packed low bits and a unary coded high part (about 2 + log2(ids a
document) bits each), with the place of every 128th one as stored select structure. Document keys are coded the same way.

Documents come in ascending key order, null keys first, equal keys by a hash of their text and by text. A null text is empty and has the end id alone.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import materialise
from .textkernel import KEPT, lean, text_batches

MAGIC = b"EBTOK2\0\0"
#: A segment is closed once it has so many ids.
SEGMENT_IDS = 2_000_000
SELECT_EVERY = 128
#: Remembered words of a Python worker at most.
MEMORY_WORDS = 800_000
#: Longer words are not remembered.
MEMORY_CHARS = 64
#: A sign in ASCII right after an ASCII or Latin-1 letter (UTF-8; not the signs of multiplication and division).
SIGN = re.compile(rb"[^a-z0-9\s\x80-\xff](?:(?<=[a-z].)|(?<=\xc3[\x80-\x96\x98-\xb6\xb8-\xbf].))", re.DOTALL)
#: Combining marks that join ASCII letters start with these bytes; A-Z may join others of them than a-z.
MARKS = re.compile(rb"[\xcc\xcd]")


def apart(text: bytes) -> bytes:
    """A text that the library gives the same ids, with fewer different words between spaces: lower case, and a space
    where it splits a sign from letters. Texts with combining marks or what may be a special token keep their letters."""
    if b"<|" not in text and not MARKS.search(text):
        text = SIGN.sub(rb" \g<0>", text.lower())
    return text.replace(b"\n", b" ")


class EliasFano:
    """A non-falling sequence of unsigned integers. samples: the places of every SELECT_EVERY-th set bit of the high part."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.samples = n, low_bits, low, high, samples

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        n = len(values)
        top = int(values[-1]) if n else 0
        low_bits = max(0, (top // n).bit_length() - 1) if n else 0
        values = values.astype(np.uint64)
        parts = ((values[:, None] >> np.arange(low_bits, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8)
        high = np.zeros((top >> low_bits) + n + 1, dtype=np.uint8)
        places = (values >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        high[places] = 1
        return cls(n, low_bits, np.packbits(parts.ravel(), bitorder="little"), np.packbits(high, bitorder="little"), places[::SELECT_EVERY].astype("<u4"))

    def select(self, i: int) -> int:
        """The i-th value, from the nearest sample on."""
        at = int(self.samples[i // SELECT_EVERY])
        left = i % SELECT_EVERY
        if left:
            at += 1
            while True:  # 64 places at a time
                window = int.from_bytes(self.high[at >> 3 : (at >> 3) + 8].tobytes(), "little") >> (at & 7)
                if (n := window.bit_count()) >= left:
                    break
                left -= n
                at = ((at >> 3) + 8) << 3
            for _ in range(left - 1):
                window &= window - 1
            at += (window & -window).bit_length() - 1
        k = i * self.low_bits
        low = int.from_bytes(self.low[k >> 3 : (k + self.low_bits + 7) >> 3].tobytes(), "little") >> (k & 7) & ((1 << self.low_bits) - 1)
        return (at - i) << self.low_bits | low

    def all(self) -> np.ndarray:
        high = np.flatnonzero(np.unpackbits(self.high, bitorder="little"))[: self.n] - np.arange(self.n)
        bits = np.unpackbits(self.low, bitorder="little")[: self.n * self.low_bits].reshape(self.n, self.low_bits).astype(np.int64)
        return (high.astype(np.int64) << self.low_bits) + bits @ (np.int64(1) << np.arange(self.low_bits, dtype=np.int64))

    def write(self) -> bytes:
        return struct.pack("<QBQQQ", self.n, self.low_bits, len(self.low), len(self.high), len(self.samples)) + self.low.tobytes() + self.high.tobytes() + self.samples.tobytes()

    @classmethod
    def read(cls, raw: bytes, at: int) -> tuple[EliasFano, int]:
        n, low_bits, a, b, c = struct.unpack_from("<QBQQQ", raw, at)
        at += struct.calcsize("<QBQQQ")
        return cls(n, low_bits, np.frombuffer(raw, np.uint8, a, at), np.frombuffer(raw, np.uint8, b, at + a), np.frombuffer(raw, "<u4", c, at + a + b)), at + a + b + 4 * c


def pack(keys: list[int | None], ends: np.ndarray, ids: bytes, width: int) -> bytes:
    nulls = sum(k is None for k in keys)
    known = np.array([k for k in keys if k is not None], dtype=np.int64)
    base = int(known[0]) if len(known) else 0
    head = MAGIC + struct.pack("<BQq", width, nulls, base)
    return b"".join((head, EliasFano.of((known - base).view(np.uint64)).write(), EliasFano.of(ends).write(), ids))


class Segment:
    """A segment read back. offsets(i) gives where document i starts and ends."""

    def __init__(self, raw: bytes):
        if raw[:8] != MAGIC:
            raise ValueError("not a token segment")
        width, self.nulls, self.base = struct.unpack_from("<BQq", raw, 8)
        keys, at = EliasFano.read(raw, 8 + struct.calcsize("<BQq"))
        self.ends, at = EliasFano.read(raw, at)
        self.key_values = keys
        self.ids = np.frombuffer(raw, dtype=f"<u{width}", offset=at)
        self._last = -1, 0

    def __len__(self) -> int:
        return self.ends.n

    def offsets(self, i: int) -> tuple[int, int]:
        """Where document i starts and ends, through the stored select structure. Reading on from the document before,
        its end is known."""
        last, end = self._last
        start = 0 if not i else end if last == i - 1 else self.ends.select(i - 1)
        self._last = i, self.ends.select(i)
        return start, self._last[1]

    def keys(self) -> list[int | None]:
        return [None] * self.nulls + (self.key_values.all() + self.base).tolist()


class WordTokenizer:
    """The tokenizers library, with the ids of words remembered: in this kind of vocabulary white space always splits
    and is dropped, and a run of letters is split from signs after it, so words are encoded apart."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.width = 2 if self.library.get_vocab_size() <= 1 << 16 else 4
        self.kind = f"<u{self.width}"
        self.words: dict[str, bytes] = {}
        last = [False] * (max(self.library.get_vocab().values()) + 1)
        for token, i in self.library.get_vocab().items():
            last[i] = token.endswith("</w>")
        self.last = np.array(last)

    def plain(self, text: str) -> bytes:
        """What the library says of a whole text."""
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype=self.kind).tobytes()

    def encode(self, text: str) -> bytes:
        return self.encode_many([text.encode()])[0].tobytes()

    def encode_many(self, texts: list[bytes | None]) -> list[np.ndarray]:
        """Ids of whole UTF-8 texts. Arrow tells the distinct words of all of them, each is looked up once, and the ids
        of the texts are gathered from those."""
        split = pc.split_pattern(pa.array([apart(t or b"") for t in texts], pa.large_binary()), " ")
        coded = split.values.dictionary_encode()
        bodies = self.look_up(coded.dictionary.cast(pa.large_string()).to_pylist())
        lengths = np.fromiter(map(len, bodies), dtype=np.int64, count=len(bodies)) // self.width
        flat = np.frombuffer(b"".join(bodies), dtype=self.kind)
        begins = np.cumsum(lengths) - lengths
        word = coded.indices.to_numpy()
        held = lengths[word]
        ends = np.concatenate(([0], np.cumsum(held)))
        ids = flat[np.repeat(begins[word] - ends[:-1], held) + np.arange(ends[-1])]
        bounds = ends[split.offsets.to_numpy()].tolist()
        return [ids[a:b] for a, b in zip(bounds, bounds[1:])]

    def look_up(self, words: list[str]) -> list[bytes]:
        """The ids of distinct words: from memory, or from the library, which gets runs of letters joined to lines and
        all others one by one."""
        known = self.words
        if len(known) > MEMORY_WORDS:
            known.clear()
        fresh = [w for w in words if w not in known]
        plain = [w for w in fresh if w.isalpha()]
        lines = [plain[i : i + 64] for i in range(0, len(plain), 64)]
        for line, got in zip(lines, self.library.encode_batch_fast([" ".join(x) for x in lines], add_special_tokens=False)):
            ids = np.array(got.ids)
            ends = ((np.flatnonzero(self.last[ids]) + 1) * self.width).tolist()
            if len(ends) == len(line):
                body = ids.astype(self.kind).tobytes()
                known.update(zip(line, (body[a:b] for a, b in zip([0, *ends], ends))))
        others = [w for w in fresh if w not in known]
        for w, got in zip(others, self.library.encode_batch_fast(others, add_special_tokens=False)):
            known[w] = np.array(got.ids, dtype=self.kind).tobytes()
        out = [known[w] for w in words]
        for w in others:
            if len(w) > MEMORY_CHARS:
                del known[w]
        return out


def tokenizer(path: str) -> WordTokenizer:
    name = f"tokens {path}"
    if name not in KEPT:
        KEPT[name] = WordTokenizer(path)
    return KEPT[name]


SEGMENTS = "part int, seq long, n_docs long, n_ids long, segment binary"


def write_segments(df: DataFrame, path: str, end_id: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The segments of a table, stored in the shared folder in key order: part and seq order them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seq = TaskContext.get().partitionId(), 0
        words = tokenizer(path)
        keys, bodies, size = [], [], 0

        def closed() -> pa.RecordBatch:
            ends = np.cumsum(np.array([len(b) for b in bodies], dtype=np.int64) + 1)
            whole = np.full(int(ends[-1]), end_id, dtype=words.kind)
            inside = np.ones(len(whole), dtype=bool)
            inside[ends - 1] = False
            whole[inside] = np.concatenate(bodies)
            blob = pack(keys, ends, whole.tobytes(), words.width)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([seq], pa.int64()), pa.array([len(keys)], pa.int64()), pa.array([int(ends[-1])], pa.int64()), pa.array([blob], pa.binary())], ["part", "seq", "n_docs", "n_ids", "segment"])

        for batch, texts in text_batches(batches):
            for k, body in zip(batch.column(0).to_pylist(), words.encode_many(texts)):
                keys.append(k)
                bodies.append(body)
                size += len(body) + 1
                if size >= SEGMENT_IDS:
                    yield closed()
                    keys, bodies, size, seq = [], [], 0, seq + 1
        if keys:
            yield closed()

    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # a hash of the text also bounds ranges, so that rows of one key, or of none, need not go to one task
    rows = df.select(F.col(key).cast("long").alias("key"), F.col(text).alias("text")).withColumn("deal", F.xxhash64("text"))
    ordered = rows.repartitionByRange(parts, "key", "deal").sortWithinPartitions("key", "deal", "text").select("key", "text")
    return materialise(ordered.mapInArrow(lean(run, "tokens"), SEGMENTS), "tokens")


def read_segments(segments: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the stored segments."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, seq, raw in zip(*(batch.column(i).to_pylist() for i in range(3))):
                segment = Segment(raw)
                ids, n = segment.ids.astype("<u4"), len(segment)
                starts, ends = np.array([segment.offsets(i) for i in range(n)], dtype=np.int64).reshape(n, 2).T
                if n and ends[-1] != len(ids):
                    raise ValueError("a segment's documents do not end where its ids end")
                sums = [zlib.crc32(ids[a:b]) for a, b in zip(starts.tolist(), ends.tolist())]
                yield pa.RecordBatch.from_arrays([pa.array([part] * n, pa.int32()), pa.array([seq] * n, pa.int64()), pa.array(segment.keys(), pa.int64()), pa.array(starts, pa.int64()), pa.array(ends - starts, pa.int64()), pa.array(sums, pa.int64())], ["part", "seq", "doc_id", "at", "n_tokens", "ids_crc32"])

    docs = segments.select("part", "seq", "segment").mapInArrow(lean(run), "part int, seq long, doc_id long, at long, n_tokens long, ids_crc32 long")
    sizes = segments.select("part", "seq", "n_ids")
    # one row a part in the single-task window: as many as tasks have written
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n")).select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before_part"))
    begins = sizes.join(parts, "part").select("part", "seq", (F.col("before_part") + F.sum("n_ids").over(Window.partitionBy("part").orderBy("seq")) - F.col("n_ids")).alias("before"))
    return docs.join(begins, ["part", "seq"]).select("doc_id", (F.col("before") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")
