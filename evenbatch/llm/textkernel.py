"""Vectorised word splitting and hashing of batches of UTF-8 texts.

Everything works on bytes: the separators of all word classes used here are ASCII, and bytes from 0x80 up
only occur inside non-ASCII characters. Words and n-grams are 64-bit fingerprints; a false match between two
given texts of a thousand n-grams each has a chance of about 1e6 / 2**64.
"""

from __future__ import annotations

import ctypes
import hashlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa

#: Texts are handled in runs of about so many bytes, which bounds the scratch arrays of a task.
RUN_BYTES = 2_000_000
#: Longer words are fingerprinted with blake2b rather than eight bytes at a time.
LONG_WORD = 2048

_M1 = np.uint64(0x9E3779B97F4A7C15)
_M2 = np.uint64(0xBF58476D1CE4E5B9)
_M3 = np.uint64(0x94D049BB133111EB)
_MASKS = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [(1 << 64) - 1], dtype=np.uint64)


def separators(keep) -> bytes:
    """A translation table: A-Z to a-z, every byte that keep() refuses to a space."""
    lowered = bytes(range(256)).lower()
    return bytes(lowered[b] if keep(lowered[b]) else 0x20 for b in range(256))


#: Words are runs without white space.
BY_SPACE = separators(lambda b: b not in (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D))
#: Words are runs of ASCII letters, digits and anything from 0x80 up.
BY_ALNUM = separators(lambda b: 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80)


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * _M2
    h = (h ^ (h >> np.uint64(27))) * _M3
    return h ^ (h >> np.uint64(31))


class Words:
    """The words of some texts in order. first[d]:first[d + 1] are those of text d."""

    __slots__ = ("data", "starts", "ends", "first")

    def __init__(self, texts: list[bytes | None], table: bytes = BY_SPACE):
        clean = [t or b"" for t in texts]
        joined = b"".join((b" ", b" ".join(clean), b" " * 9)).translate(table)
        self.data = np.frombuffer(joined, dtype=np.uint8)
        mask = self.data != 0x20
        edge = np.flatnonzero(mask[1:] != mask[:-1]) + 1
        self.starts, self.ends = edge[0::2], edge[1::2]
        at = np.cumsum(np.fromiter((len(t) + 1 for t in clean), dtype=np.int64, count=len(clean)))
        self.first = np.concatenate(([0], np.searchsorted(self.starts, at + 1)))

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def word(self, i: int) -> bytes:
        return self.data[self.starts[i] : self.ends[i]].tobytes()

    def hashes(self) -> np.ndarray:
        """A 64-bit fingerprint of each word."""
        lens = self.ends - self.starts
        h = lens.astype(np.uint64) * _M1
        loads = np.ndarray((len(self.data) - 7,), dtype="<u8", buffer=self.data, strides=(1,))
        h = mix(h ^ (loads[self.starts] & _MASKS[np.minimum(lens, 8)]))
        todo, done = np.flatnonzero((lens > 8) & (lens <= LONG_WORD)), 8
        while len(todo):
            left = lens[todo] - done
            h[todo] = mix(h[todo] ^ (loads[self.starts[todo] + done] & _MASKS[np.minimum(left, 8)]))
            todo, done = todo[left > 8], done + 8
        for i in np.flatnonzero(lens > LONG_WORD):
            h[i] = np.frombuffer(hashlib.blake2b(self.word(i), digest_size=8).digest(), dtype="<u8")[0]
        return h


def ngrams(h: np.ndarray, n: int) -> np.ndarray:
    """Fingerprints of all n consecutive words, whatever text they are of."""
    if len(h) < n:
        return np.empty(0, dtype=np.uint64)
    acc = np.zeros(len(h) - n + 1, dtype=np.uint64)
    for k in range(n):
        acc = acc * _M1 + h[k : len(h) - n + 1 + k]
    return mix(acc)


def distinct(values: np.ndarray) -> np.ndarray:
    """The sorted distinct values."""
    values = np.sort(values)
    keep = np.empty(len(values), dtype=bool)
    keep[:1] = True
    np.not_equal(values[1:], values[:-1], out=keep[1:])
    return values[keep]


def shingle_sets(texts: list[bytes | None], n: int, table: bytes = BY_SPACE) -> Iterator[np.ndarray]:
    """The sorted distinct n-word shingles of each text; fewer words make one shingle, none an empty set."""
    words = Words(texts, table)
    h = words.hashes()
    grams = ngrams(h, n)
    first = words.first
    for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
        if b - a >= n:
            yield distinct(grams[a : b - n + 1])
        elif b > a:
            yield ngrams(h[a:b], b - a)
        else:
            yield np.empty(0, dtype=np.uint64)


def runs(texts: Iterable[bytes | None]) -> Iterator[tuple[int, int]]:
    """Index ranges whose texts have about RUN_BYTES together; a longer text is a range of its own."""
    start, size, i = 0, 0, 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if size and size + n > RUN_BYTES:
            yield start, i
            start, size = i, 0
        size += n + 1
    if size:
        yield start, i + 1


def as_bytes(column: pa.Array) -> list[bytes | None]:
    """UTF-8 bytes of a string column."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist() if not pa.types.is_binary(column.type) else column.to_pylist()


def text_batches(batches: Iterable[pa.RecordBatch], text: str = "text") -> Iterator[tuple[pa.RecordBatch, list[bytes | None]]]:
    """Parts of the batches of which each has about RUN_BYTES of text, with their texts as bytes."""
    for batch in batches:
        texts = as_bytes(batch.column(batch.schema.get_field_index(text)))
        for a, b in runs(texts):
            yield batch.slice(a, b - a), texts[a:b]


#: What the Python worker keeps between the tasks of an operator, by operator.
KEPT: dict[str, object] = {}


def tidy() -> None:
    """Give free memory back to the machine: Arrow and the C library keep it otherwise."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def _only(keeps: str) -> None:
    for name in [k for k in KEPT if not k.startswith(keeps or "-")]:
        del KEPT[name]
    tidy()


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], keeps: str = "") -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """run, for mapInArrow, with little memory left behind: Spark's Python workers go from the tasks of one operator to
    those of the next. A task first drops what other operators have kept in its worker (all of KEPT but names that begin
    with keeps) and gives memory back when it ends."""

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _only(keeps)
        try:
            yield from run(batches)
        finally:
            tidy()

    return held
