"""Benchmark decontamination as a prefix-filtered set join.

Each item is cut into windows of ten consecutive words (a shorter item is one window). A window's shingles are its
runs of up to five words, put in order of rarity over the whole corpus; as a document must contain a window whole, its
rarest shingle alone is the necessary prefix. Spark joins the documents' shingles with these prefixes; the length and
positional bounds say whether the window fits around the match inside the document, and the words there are then
compared, as words, with those of the window. Windows that several items share are looked for once.

Neither side is gathered anywhere: windows and owners are tables. What is broadcast has a fixed size (a count table of
cells, and filters that only spare shuffles) or has been counted first (windows, up to BROADCAST_WINDOWS of them); more
windows are joined in a shuffle, dealt over DEALS parts for shingles that very many documents have.

Texts and items may be null, empty or without words: they have no windows and no hits. Repeated items and windows
count once; repeated documents are rows of their own; a null item id counts as the text `null`. Further columns are not
read, or kept as they are, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, StructField, StructType

from .sieve import passes, sieve_of
from .storage import discard, materialise, send
from .textkernel import BY_ALNUM, Words, lean, ngrams, text_batches

WINDOW = 10
SHINGLE = 5
#: Cells of the count table, as a power of two.
CELL_BITS = 20
#: Windows that are broadcast at most (some 100 bytes each), and the parts of a shuffled join that one shingle goes to.
BROADCAST_WINDOWS = 200_000
DEALS = 16


def windows_of(benchmark: DataFrame, item: str = "item_id", text: str = "text") -> DataFrame:
    """(window, n, item): the distinct windows of each item, as n words with a space between."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_batches(batches):
            words = Words(texts, BY_ALNUM)
            said = [words.word(i).decode(errors="replace") for i in range(len(words.starts))]
            first, names = words.first.tolist(), batch.column(0).to_pylist()
            rows = {(" ".join(said[s : min(b, s + WINDOW)]), min(b - s, WINDOW), x) for x, a, b in zip(names, first[:-1], first[1:]) for s in range(a, max(a + 1, b - WINDOW + 1) if b > a else a)}
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.string())], ["window", "n", "item"])

    items = benchmark.select(F.coalesce(F.col(item).cast("string"), F.lit("null")).alias("item"), F.col(text).alias("text"))
    return materialise(items.mapInArrow(lean(run), "window string, n int, item string").distinct(), "windows")


def _grams(window: str) -> np.ndarray:
    h = Words([window.encode()], BY_ALNUM).hashes()
    return ngrams(h, min(SHINGLE, len(h)))


def shingles_of(windows: DataFrame) -> DataFrame:
    """(gram): the shingles of the full length of all windows; shorter windows have one alone, and no choice."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            grams = [_grams(w) for w in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(np.concatenate(grams)).view(np.int64) if grams else [], pa.int64())], ["gram"])

    return windows.where(F.col("n") >= SHINGLE).select("window").mapInArrow(lean(run), "gram long").distinct()


def _cell(grams: np.ndarray) -> np.ndarray:
    return (grams >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def count_cells(texts: DataFrame, sieve: np.ndarray) -> np.ndarray:
    """How often shingles that the sieve knows occur in all texts, by cells: 2**CELL_BITS counts, whatever the input."""
    shared = send(texts.sparkSession, sieve)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(1 << CELL_BITS, dtype=np.int64)
        for _, raw in text_batches(batches):
            grams = ngrams(Words(raw, BY_ALNUM).hashes(), SHINGLE)
            seen += np.bincount(_cell(grams[passes(shared.value, grams.view(np.int64))]), minlength=len(seen))
        hit = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(hit, pa.int64()), pa.array(seen[hit], pa.int64())], ["cell", "seen"])

    out = np.zeros(1 << CELL_BITS, dtype=np.int64)
    for r in texts.mapInArrow(lean(run), "cell long, seen long").groupBy("cell").agg(F.sum("seen").alias("seen")).toLocalIterator():
        out[r["cell"]] = r["seen"]
    shared.unpersist()
    return out


def prefixes_of(windows: DataFrame, cells: np.ndarray) -> DataFrame:
    """(gram, size, skip, window, n): each distinct window with its rarest shingle (of equally rare ones that with the
    smallest fingerprint), the shingle's length, and the words before it."""
    shared = send(windows.sparkSession, cells)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for w, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                grams = _grams(w)
                k = int(np.lexsort((grams, shared.value[_cell(grams)]))[0])
                out.append((int(grams[k : k + 1].view(np.int64)[0]), min(SHINGLE, n), k, w, n))
            kinds = [pa.int64(), pa.int32(), pa.int32(), pa.string(), pa.int32()]
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], t) for i, t in enumerate(kinds)], ["gram", "size", "skip", "window", "n"])

    return materialise(windows.select("window", "n").distinct().mapInArrow(lean(run), "gram long, size int, skip int, window string, n int"), "prefixes")


def text_print(text: bytes | None) -> bytes:
    return hashlib.blake2b(text or b"", digest_size=16).digest()


def matches_of(docs: DataFrame, prefixes: DataFrame, by_text: bool) -> DataFrame:
    """Rows of kind 0, one a document unless by_text: id, key, n_words. Rows of kind 1: id, gram, size, place (of the
    shingle in the document), lead (words before it in near) and near (the words around it that a window may have). An id
    is a row's number, or by_text the print of its text. docs has the columns key, text."""
    spark = docs.sparkSession
    lengths = sorted(r["size"] for r in prefixes.select("size").distinct().collect())  # SHINGLE rows at most
    sieves = send(spark, {n: sieve_of(prefixes.where(F.col("size") == n).select("gram").distinct()) for n in lengths})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 40
        for batch, texts in text_batches(batches):
            words = Words(texts, BY_ALNUM)
            first, h, k = words.first, words.hashes(), len(texts)
            ids = [text_print(t) for t in texts] if by_text else [(number + i).to_bytes(8, "big") for i in range(k)]
            number += k
            if not by_text:
                blank = lambda t: pa.nulls(k, t)
                yield pa.RecordBatch.from_arrays([pa.array([0] * k, pa.int32()), pa.array(ids, pa.binary()), batch.column(0), pa.array(words.counts(), pa.int64()), blank(pa.int64()), blank(pa.int32()), blank(pa.int64()), blank(pa.int32()), blank(pa.string())], names)
            out = []
            for n, sieve in sieves.value.items():
                grams = ngrams(h, n)
                at = np.flatnonzero(passes(sieve, grams.view(np.int64))) if len(grams) else np.empty(0, int)
                doc = np.searchsorted(first, at, side="right") - 1
                inside = at + n <= first[doc + 1]
                for p, d in zip(at[inside].tolist(), doc[inside].tolist()):
                    a, b = max(int(first[d]), p - WINDOW + n), min(int(first[d + 1]), p + WINDOW)
                    out.append((ids[d], int(grams[p : p + 1].view(np.int64)[0]), n, p - int(first[d]), p - a, b" ".join([words.word(i) for i in range(a, b)]).decode(errors="replace")))
            m, column = len(out), lambda i, t: pa.array([x[i] for x in out], t)
            yield pa.RecordBatch.from_arrays([pa.array([1] * m, pa.int32()), column(0, pa.binary()), pa.nulls(m, batch.column(0).type), pa.nulls(m, pa.int64()), column(1, pa.int64()), column(2, pa.int32()), column(3, pa.int64()), column(4, pa.int32()), column(5, pa.string())], names)

    names = ["kind", "id", "key", "n_words", "gram", "size", "place", "lead", "near"]
    schema = f"kind int, id binary, key {dict(docs.dtypes)['key']}, n_words long, gram long, size int, place long, lead int, near string"
    return materialise(docs.select("key", "text").mapInArrow(lean(run), schema), "matches", ("kind",))


def hits_of(matches: DataFrame, prefixes: DataFrame) -> DataFrame:
    """(id, start, n, window): where windows occur, in words."""
    found = matches.where("kind = 1").select("id", "gram", "size", "place", "lead", "near")
    if prefixes.count() <= BROADCAST_WINDOWS:
        pairs = found.join(F.broadcast(prefixes), ["gram", "size"])
    else:
        dealt = prefixes.withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(DEALS - 1))))
        pairs = found.withColumn("deal", F.pmod(F.xxhash64("id", "place"), F.lit(DEALS)).cast("int")).join(dealt, ["gram", "size", "deal"])
    begin = F.col("lead") - F.col("skip")
    around = F.split("near", " ")
    pairs = pairs.where((begin >= 0) & (begin + F.col("n") <= F.size(around)))
    same = F.array_join(F.slice(around, begin + 1, F.col("n")), " ") == F.col("window")
    return pairs.where(same).select("id", (F.col("place") - F.col("skip")).alias("start"), "n", "window")


def _covered(spans: str):
    """How many words the (start, n) of an array cover together."""
    zero = F.struct(F.lit(0).cast("long").alias("total"), F.lit(0).cast("long").alias("reached"))

    def add(acc, x):
        end = x["start"] + x["n"]
        return F.struct((acc["total"] + F.greatest(F.lit(0).cast("long"), end - F.greatest(x["start"], acc["reached"]))).alias("total"), F.greatest(end, acc["reached"]).alias("reached"))

    return F.aggregate(F.array_sort(spans), zero, add, lambda acc: acc["total"])


def _prefixes(texts: DataFrame, benchmark: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(windows with their items, prefixes)."""
    windows = windows_of(benchmark)
    return windows, prefixes_of(windows, count_cells(texts, sieve_of(shingles_of(windows))))


def find_items(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_words, n_hit, n_items, items_sha256, contaminated of every row of docs."""
    rows = docs.select(F.col(key).alias("key"), F.col(text).alias("text"))
    windows, prefixes = _prefixes(rows.select("text"), benchmark)
    matches = matches_of(rows, prefixes, by_text=False)
    hits = materialise(hits_of(matches, prefixes), "hits")
    spans = hits.groupBy("id").agg(F.collect_set(F.struct("start", "n")).alias("spans")).select("id", _covered("spans").alias("n_hit"))
    # a window that very many documents have meets its items once a deal
    owners = windows.select("window", "item").withColumn("deal", F.explode(F.sequence(F.lit(0), F.lit(DEALS - 1))))
    owned = hits.select("id", "window").distinct().withColumn("deal", F.pmod(F.xxhash64("id"), F.lit(DEALS)).cast("int")).join(owners, ["window", "deal"])
    items = owned.groupBy("id").agg(F.array_sort(F.collect_set("item")).alias("items")).select("id", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("said"))
    none = hashlib.sha256(b"").hexdigest()
    n_hit = F.coalesce("n_hit", F.lit(0).cast("long"))
    return matches.where("kind = 0").select("id", "key", "n_words").join(spans, "id", "left").join(items, "id", "left").select(
        F.col("key").alias(key), "n_words", n_hit.alias("n_hit"), F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"), F.coalesce("said", F.lit(none)).alias("items_sha256"), (n_hit > 0).alias("contaminated")
    )


def keep_clean(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, in which no window of any item occurs. Texts that a filter of the
    contaminated texts' prints does not know go straight on; the others are checked by a join."""
    rows = docs.select(F.lit(None).cast("string").alias("key"), F.col(text).alias("text"))
    _, prefixes = _prefixes(rows.select("text"), benchmark)
    matches = matches_of(rows, prefixes, by_text=True)
    mark = "_text_print"
    while mark in docs.columns:
        mark += "_"
    bad = materialise(hits_of(matches, prefixes).select(F.col("id").alias(mark)).distinct(), "contaminated")
    short = F.conv(F.hex(F.substring(mark, 2, 7)), 16, 10).cast("long")  # seven bytes fit a BIGINT
    shared = send(docs.sparkSession, sieve_of(bad.select(short.alias("short"))))
    discard(matches)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_batches(batches, text):
            prints = [text_print(t) for t in texts]
            maybe = passes(shared.value, np.array([int.from_bytes(x[1:8], "big") for x in prints], dtype=np.int64))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([x if m else None for x, m in zip(prints, maybe)], pa.binary())], [*batch.schema.names, mark])

    marked = docs.mapInArrow(lean(run), StructType([*docs.schema.fields, StructField(mark, BinaryType())]))
    known, open_ = marked.where(F.col(mark).isNull()), marked.where(F.col(mark).isNotNull())
    return known.unionByName(open_.join(bad, mark, "left_anti")).drop(mark)


ORACLE: str = r"""
    WITH d AS (SELECT doc_id, row_number() OVER () AS r, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
    b AS (SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
    win AS (SELECT DISTINCT item, array_to_string(w[i : least(len(w), i + 9)], ' ') AS g, least(len(w), 10) AS n FROM b, unnest(range(1, greatest(2, len(w) - 8))) AS u(i) WHERE len(w) > 0),
    sizes AS (SELECT DISTINCT n FROM win),
    pos AS (SELECT r, i, n, array_to_string(w[i : i + n - 1], ' ') AS g FROM d, sizes, unnest(range(1, len(w) + 1)) AS u(i) WHERE i + n - 1 <= len(w)),
    hit AS (SELECT r, i, pos.n, item FROM pos JOIN win ON pos.g = win.g AND pos.n = win.n),
    cov AS (SELECT r, count(DISTINCT i + k) AS n_hit FROM hit, unnest(range(0, n)) AS u(k) GROUP BY r),
    its AS (SELECT r, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS said FROM hit GROUP BY r)
    SELECT doc_id, CAST(coalesce(len(w), 0) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(said, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
    FROM d LEFT JOIN cov USING (r) LEFT JOIN its USING (r)"""
