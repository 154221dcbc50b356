"""A class-based n-gram model: exchange clustering puts words into classes, and class transitions and word emissions,
both smoothed, give a text's probability.

Passes over the text: counts of all words; transitions between the SEEDS most frequent words, the shapes of all others
and the end of a text, on which sequential exchange forms the classes; ROUNDS rounds of exchange of all KEEP known words
against these classes, each word by its own counts of the classes beside it, which Spark adds up; transitions between
the final classes; scores. The count table stays distributed. The KEEP most frequent words are broadcast; the counts of
rarer words, which go by their shape, come from the distributed table by a shuffle of packed fingerprints, so every
count is exact.

A null or empty text is its end alone. Rows that repeat an id are scored each. Without training rows all counts are 0.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import materialise, send
from .textkernel import Words, lean, text_batches

#: Words that are broadcast with their counts and classes at most, words that form the classes, and classes.
KEEP = 300_000
SEEDS = 1000
CLASSES = 48
SWEEPS = 4
#: Rounds in which all known words may change their class, and words of one part of a round.
ROUNDS = 1
ROUND_WORDS = 2_000
#: Weight of the class frequencies in a transition.
PRIOR = 20.0
#: Text bytes that give the count table one part, and words that a task gathers before it sends them.
PART_BYTES = 24_000_000
FLUSH_WORDS = 4_000_000
#: Tasks whose counts are added up before those of all tasks meet.
FAN = 64
SHAPES = 6


def shapes_of(words: Words) -> np.ndarray:
    """0 to 5: whether a word ends with a full stop, comma or neither, and has a byte from 0x80 up."""
    last = words.data[words.ends - 1] if len(words.ends) else np.empty(0, dtype=np.uint8)
    wide = np.concatenate(([0], np.cumsum(words.data >= 0x80)))
    return np.where(last == 0x2E, 0, np.where(last == 0x2C, 1, 2)) + 3 * (wide[words.ends] > wide[words.starts])


def _packed(part: np.ndarray, columns: list[np.ndarray], names: list[str]) -> pa.RecordBatch:
    """One row a part, each with the bytes of its share of the columns."""
    by = np.argsort(part, kind="stable")
    keys, begin = np.unique(part[by], return_index=True)
    cut = [np.split(c[by], begin[1:]) if len(keys) else [] for c in columns]
    return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), *(pa.array([x.tobytes() for x in c], pa.binary()) for c in cut)], names)


def _joined(frame: pd.DataFrame, name: str, kind) -> np.ndarray:
    return np.concatenate([np.frombuffer(x, dtype=kind) for x in frame[name]]) if len(frame) else np.empty(0, dtype=kind)


def _summed(keys: np.ndarray, counts: np.ndarray, more: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    by = np.argsort(keys, kind="stable")
    keys, counts, more = keys[by], counts[by], more[by]
    begin = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.empty(0, int)
    return keys[begin], np.add.reduceat(counts, begin) if len(keys) else counts, more[begin]


def _added(packed: DataFrame, by: str, add) -> DataFrame:
    """The counts of each FAN tasks in a row a value of by, so that nobody gets a row from every task."""
    near = packed.withColumn("fan", (F.spark_partition_id() / FAN).cast("int"))
    return near.groupBy(by, "fan").applyInPandas(add, packed.schema)


def count_words(texts: DataFrame, parts: int) -> DataFrame:
    """(part, words, counts, shapes): fingerprints by part, each once, with its count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            h, c, s = _summed(*(np.concatenate(x) for x in zip(*held)))
            return _packed((h % np.uint64(parts)).astype(np.int64), [h, c, s], ["part", "words", "counts", "shapes"])

        for _, raw in text_batches(batches):
            words = Words(raw)
            h, s = words.hashes(), shapes_of(words).astype(np.uint8)
            held.append(_summed(h, np.ones(len(h), dtype=np.int64), s))
            size += len(held[-1][0])
            if size >= FLUSH_WORDS:
                yield flush()
                held, size = [], 0
        if size:
            yield flush()

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        h, c, s = _summed(_joined(frame, "words", np.uint64), _joined(frame, "counts", np.int64), _joined(frame, "shapes", np.uint8))
        return pd.DataFrame({"part": [frame["part"].iloc[0]], "words": [h.tobytes()], "counts": [c.tobytes()], "shapes": [s.tobytes()]})

    schema = "part long, words binary, counts binary, shapes binary"
    return materialise(texts.mapInArrow(lean(run), schema).groupBy("part").applyInPandas(add, schema), "words")


def xlogx(x):
    return x * np.log(np.maximum(x, 1e-300))


def exchange(bigrams: np.ndarray, movable: int, classes: int, sweeps: int) -> np.ndarray:
    """Classes of symbols, from how often each follows each: move each of the first movable symbols to the class that
    raises the mutual information of neighbouring classes most, in at most so many sweeps. The symbols behind them
    are classes of their own, which count as neighbours."""
    n = len(bigrams)
    classes = max(1, min(classes, movable))
    of = np.concatenate((np.arange(movable) % classes, classes + np.arange(n - movable))).astype(int)
    member = np.zeros((n, classes + n - movable))
    member[np.arange(n), of] = 1
    table = member.T @ bigrams @ member
    for _ in range(sweeps):
        moved = 0
        for w in range(movable):
            right, left, own = bigrams[w] @ member, bigrams[:, w] @ member, bigrams[w, w]
            k = of[w]
            right[k] -= own
            left[k] -= own
            table[k] -= right
            table[:, k] -= left
            table[k, k] -= own
            rows, columns = table.sum(1), table.sum(0)
            gain = (xlogx(table + right) - xlogx(table)).sum(1) + (xlogx(table + left[:, None]) - xlogx(table)).sum(0)
            d = np.diag(table)
            gain += xlogx(d + right + left + own) - xlogx(d + right) - xlogx(d + left) + xlogx(d)
            gain -= xlogx(rows + right.sum() + own) - xlogx(rows) + xlogx(columns + left.sum() + own) - xlogx(columns)
            best = int(gain[:classes].argmax())
            if gain[best] <= gain[k] + 1e-9:
                best = k
            moved += best != k
            member[w, k], member[w, best], of[w] = 0, 1, best
            table[best] += right
            table[:, best] += left
            table[best, best] += own
        if not moved:
            break
    return of


def better_classes(word: np.ndarray, side: np.ndarray, beside: np.ndarray, seen: np.ndarray, own: np.ndarray, table: np.ndarray, free: int) -> np.ndarray:
    """The class, of the first free ones or its own, that suits each word best in a fixed table of class transitions.
    word, side (0: before, 1: behind it), beside, seen: how often a class stands beside a word, sorted by word 0, 1, ..;
    own: each word's class."""
    out = own.copy()
    margins = (table.sum(0), table.sum(1))
    begin = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1]))) if len(word) else np.empty(0, int)
    for first in range(0, len(begin), 4096):
        a, b = begin[first], begin[first + 4096] if first + 4096 < len(begin) else len(word)
        w, s, j, v = word[a:b], side[a:b], beside[a:b], seen[a:b].astype(float)[:, None]
        cells = np.where(s[:, None] == 1, table[:, j].T, table[j])  # what each class has beside that class
        cells[np.arange(len(w)), own[w]] -= v[:, 0]
        cells = np.maximum(cells, 0)
        at = begin[first : first + 4096] - a
        gain = np.add.reduceat(xlogx(cells + v) - xlogx(cells), at, axis=0)
        words = w[at]
        for d in (0, 1):
            total = np.add.reduceat(np.where(s == d, v[:, 0], 0.0), at)[:, None]
            margin = np.repeat(margins[d][None], len(words), axis=0)
            margin[np.arange(len(words)), own[words]] -= total[:, 0]
            margin = np.maximum(margin, 0)
            gain -= xlogx(margin + total) - xlogx(margin)
        stay = gain[np.arange(len(words)), own[words]]
        best = gain[:, :free].argmax(1) if free else own[words]
        move = gain[np.arange(len(words)), best] > stay + 1e-9
        out[words[move]] = best[move]
    return out


@dataclass
class Model:
    """known: fingerprints of the most frequent words, sorted, with counts, shapes, places among the seeds (-1: none)
    and classes. Behind the free classes come those of the shapes and the end."""

    known: np.ndarray
    counts: np.ndarray
    shape: np.ndarray
    seed: np.ndarray
    n_seeds: int
    train_tokens: int
    vocabulary: int
    ends: int
    free: int = 0
    kind: np.ndarray | None = None
    transition: np.ndarray | None = None
    emission_total: np.ndarray | None = None

    @property
    def classes(self) -> int:
        return self.free + SHAPES + 1

    def _sequence(self, words: Words, own: np.ndarray, others: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        h = words.hashes()
        at = np.searchsorted(self.known, h)
        at[at == len(self.known)] = 0
        at = np.where(self.known[at] == h, at, -1) if len(self.known) else np.full(len(h), -1)
        said = np.where(at >= 0, own[at], -1) if len(self.known) else at
        said = np.where(said >= 0, said, others + shapes_of(words))
        out = np.full(len(h) + len(words.first) - 1, others + SHAPES)
        out[self.places(words)] = said
        return out, at, h

    @staticmethod
    def places(words: Words) -> np.ndarray:
        """Where the words stand in a sequence with an end behind each text."""
        return np.arange(len(words.starts)) + np.repeat(np.arange(len(words.first) - 1), words.counts())

    def seeds_of(self, words: Words) -> np.ndarray:
        """Seeds, shapes of other words, and an end after each text."""
        return self._sequence(words, self.seed, self.n_seeds)[0]

    def classes_of(self, words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(classes with an end after each text, places of the words in known or -1, fingerprints)."""
        return self._sequence(words, self.kind, self.free)


def _table_of(counted: DataFrame, ends: int) -> Model:
    """The frequent words, and the sizes of the whole table."""

    def sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw in batch.column(0).to_pylist():
                c, times = np.unique(np.frombuffer(raw, dtype=np.int64), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()), pa.array(times, pa.int64())], ["seen", "times"])

    spread = counted.select("counts").mapInArrow(lean(sizes), "seen long, times long").groupBy("seen").agg(F.sum("times").alias("times")).orderBy(F.desc("seen"))
    tokens, types, least, kept = 0, 0, 1 << 62, 0
    for r in spread.toLocalIterator():  # a row a distinct count, whose number grows with the root of the input
        tokens, types, kept = tokens + r["seen"] * r["times"], types + r["times"], kept + r["times"]
        if kept <= KEEP:  # all words that occur so often, or more often, fit
            least = r["seen"]

    def frequent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for w, c, s in zip(*(batch.column(i).to_pylist() for i in range(3))):
                w, c, s = np.frombuffer(w, dtype=np.uint64), np.frombuffer(c, dtype=np.int64), np.frombuffer(s, dtype=np.uint8)
                hit = c >= least
                yield pa.RecordBatch.from_arrays([pa.array([x[hit].tobytes()], pa.binary()) for x in (w, c, s)], ["words", "counts", "shapes"])

    rows = list(counted.select("words", "counts", "shapes").mapInArrow(lean(frequent), "words binary, counts binary, shapes binary").toLocalIterator())
    known, counts, shape = (np.concatenate([np.frombuffer(r[name], dtype=t) for r in rows] or [np.empty(0, t)]) for name, t in (("words", np.uint64), ("counts", np.int64), ("shapes", np.uint8)))
    by = np.argsort(known)
    known, counts, shape = known[by], counts[by], shape[by]
    top = np.lexsort((known, -counts))[:SEEDS]
    seed = np.full(len(known), -1)
    seed[top] = np.arange(len(top))
    return Model(known, counts, shape, seed, len(top), tokens + ends, types + (ends > 0), ends)


def _bigrams(texts: DataFrame, shared, size: int, of_seeds: bool) -> np.ndarray:
    """How often each seed (shape, end) follows each, or each class."""
    rows = 64

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size * size, dtype=np.int64)
        for _, raw in text_batches(batches):
            m, words = shared.value, Words(raw)
            seq = m.seeds_of(words) if of_seeds else m.classes_of(words)[0]
            before = np.concatenate(([size - 1], seq[:-1]))
            total += np.bincount(before * size + seq, minlength=size * size)
        hit = np.flatnonzero(total)
        if len(hit):
            yield _packed(hit // size // rows, [hit, total[hit]], ["slice", "at", "seen"])

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        at, seen, _ = _summed(_joined(frame, "at", np.int64), _joined(frame, "seen", np.int64), np.zeros(sum(len(x) for x in frame["at"]) // 8))
        return pd.DataFrame({"slice": [frame["slice"].iloc[0]], "at": [at.tobytes()], "seen": [seen.tobytes()]})

    schema = "slice long, at binary, seen binary"
    out = np.zeros(size * size)
    for r in _added(texts.mapInArrow(lean(run), schema), "slice", add).groupBy("slice").applyInPandas(add, schema).toLocalIterator():
        out[np.frombuffer(r["at"], dtype=np.int64)] = np.frombuffer(r["seen"], dtype=np.int64)
    return out.reshape(size, size)


def _exchanged(texts: DataFrame, model: Model, table: np.ndarray) -> np.ndarray:
    """The classes of all known words after a round of exchange against the classes of table."""
    width = 2 * model.classes
    shared = send(texts.sparkSession, (model, table))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value[0]
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0

        def summed() -> tuple[np.ndarray, np.ndarray]:
            keys, seen = (np.concatenate(x) for x in zip(*held))
            return _summed(keys, seen, np.zeros(len(keys), dtype=np.uint8))[:2]

        for _, raw in text_batches(batches):
            words = Words(raw)
            seq, at, _ = m.classes_of(words)
            place, known = m.places(words), np.flatnonzero(at >= 0)
            before = np.concatenate(([m.classes - 1], seq[:-1]))
            base = at[known] * width
            held.append(np.unique(np.concatenate((base + before[place[known]], base + m.classes + seq[place[known] + 1])), return_counts=True))
            size += len(held[-1][0])
            if size >= FLUSH_WORDS:
                held = [summed()]
                size = len(held[0][0])
                if size >= FLUSH_WORDS // 2:
                    yield _packed(held[0][0] // (width * ROUND_WORDS), list(held[0]), ["part", "keys", "seen"])
                    held, size = [], 0
        if size:
            keys, seen = summed()
            yield _packed(keys // (width * ROUND_WORDS), [keys, seen], ["part", "keys", "seen"])

    def total(frame: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
        keys, seen = _joined(frame, "keys", np.int64), _joined(frame, "seen", np.int64)
        return _summed(keys, seen, np.zeros(len(keys), dtype=np.uint8))[:2]

    def add(frame: pd.DataFrame) -> pd.DataFrame:
        keys, seen = total(frame)
        return pd.DataFrame({"part": [frame["part"].iloc[0]], "keys": [keys.tobytes()], "seen": [seen.tobytes()]})

    def choose(frame: pd.DataFrame) -> pd.DataFrame:
        m, transitions = shared.value
        keys, seen = total(frame)
        first = int(frame["part"].iloc[0]) * ROUND_WORDS
        word, rest = keys // width - first, keys % width
        kinds = better_classes(word, rest // m.classes, rest % m.classes, seen, m.kind[first : first + ROUND_WORDS], transitions, m.free)
        return pd.DataFrame({"part": [first // ROUND_WORDS], "kinds": [kinds.astype(np.int32).tobytes()]})

    out = model.kind.copy()
    counted = _added(texts.mapInArrow(lean(run), "part long, keys binary, seen binary"), "part", add)
    for r in counted.groupBy("part").applyInPandas(choose, "part long, kinds binary").toLocalIterator():
        kinds = np.frombuffer(r["kinds"], dtype=np.int32)
        out[r["part"] * ROUND_WORDS : r["part"] * ROUND_WORDS + len(kinds)] = kinds
    shared.unpersist()
    return out


def train(texts: DataFrame, parts: int) -> tuple[Model, DataFrame]:
    """The model, and the whole count table it was made from. texts has one column, text."""
    spark = texts.sparkSession
    counted = count_words(texts, parts)
    model = _table_of(counted, texts.count())
    w = model.n_seeds
    size = w + SHAPES + 1
    shared = send(spark, model)
    bigrams = _bigrams(texts, shared, size, True)
    shared.unpersist()
    of = exchange(bigrams, w, CLASSES, SWEEPS)
    model.free = int(of.max()) - SHAPES if w else 0
    if not w:
        of = np.arange(size)
    member = np.zeros((size, model.classes))
    member[np.arange(size), of] = 1
    table = member.T @ bigrams @ member
    model.kind = np.where(model.seed >= 0, of[model.seed], model.free + model.shape).astype(np.int64)
    for _ in range(ROUNDS):
        model.kind = _exchanged(texts, model, table)
        shared = send(spark, model)
        table = _bigrams(texts, shared, model.classes, False)
        shared.unpersist()
    here = table.sum(0)
    share = (here + 0.5) / (here.sum() + 0.5 * model.classes)
    model.transition = np.log10((table + PRIOR * share) / (table.sum(1, keepdims=True) + PRIOR))
    # types of each class: its known words; of a shape, all other words of that shape too
    types = np.bincount(model.kind, minlength=model.classes).astype(float)
    types[model.free : model.free + SHAPES] += _shape_types(counted, model)
    model.emission_total = here + 0.5 * (types + 1)
    return model, counted


def _shape_types(counted: DataFrame, model: Model) -> np.ndarray:
    """How many words of each shape there are besides the known ones."""
    shared = send(counted.sparkSession, model.known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(SHAPES, dtype=np.int64)
        for batch in batches:
            for w, s in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                total += np.bincount(np.frombuffer(s, dtype=np.uint8)[~np.isin(np.frombuffer(w, dtype=np.uint64), shared.value)], minlength=SHAPES)
        yield pa.RecordBatch.from_arrays([pa.array(range(SHAPES), pa.int64()), pa.array(total, pa.int64())], ["shape", "types"])

    out = np.zeros(SHAPES)
    for r in counted.select("words", "shapes").mapInArrow(lean(run), "shape long, types long").groupBy("shape").agg(F.sum("types").alias("types")).toLocalIterator():
        out[r["shape"]] = r["types"]
    return out


def score(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, held_out, n_tokens, n_known, train_tokens, base_score, score of every row; rows whose crc32(key) mod 5 is
    not 1 are learned from."""
    spark = docs.sparkSession
    held = F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")) % 5 == 1
    rows = docs.select(F.col(key).alias("key"), held.alias("held_out"), F.col(text).alias("text"))
    parts = int((rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // PART_BYTES + 1)
    model, counted = train(rows.where(~F.col("held_out")).select("text"), parts)
    shared = send(spark, model)
    whole = model.train_tokens + 0.5 * (model.vocabulary + 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        m, task, n = shared.value, TaskContext.get().partitionId(), 0
        for batch, raw in text_batches(batches):
            words = Words(raw)
            classes, at, h = m.classes_of(words)
            first = words.first[:-1] + np.arange(len(raw))
            place = m.places(words)
            before = np.concatenate(([m.classes - 1], classes[:-1]))
            here = np.where(at >= 0, np.log10(m.counts[at] + 0.5), 0.0) if len(m.known) else np.zeros(len(h))
            base, mine = np.full(len(classes), np.log10(m.ends + 0.5)), m.transition[before, classes]
            base[place] = here
            mine[place] += here - np.log10(m.emission_total[classes[place]])
            known = np.full(len(classes), int(m.ends > 0))
            known[place] = at >= 0
            ids = np.arange(n, n + len(raw)) + (task << 36)
            n += len(raw)
            total = lambda x: np.add.reduceat(x, first)
            empty = pa.nulls(len(raw), pa.binary())
            counts = words.counts() + 1
            names = ["kind", "row", "part", "key", "held_out", "n_tokens", "n_known", "base_score", "score", "words", "rows"]
            yield pa.RecordBatch.from_arrays(
                [pa.array([0] * len(raw), pa.int32()), pa.array(ids, pa.int64()), pa.array([task] * len(raw), pa.int64()), batch.column(0), batch.column(1), pa.array(counts, pa.int64()), pa.array(total(known), pa.int64()),
                 pa.array(total(base) - counts * np.log10(whole), pa.float64()), pa.array(total(mine), pa.float64()), empty, empty], names)
            rare = np.flatnonzero(at < 0)
            if len(rare):
                owner = np.repeat(ids, words.counts())[rare]
                asked = _packed((h[rare] % np.uint64(parts)).astype(np.int64), [h[rare], owner], ["part", "words", "rows"])
                k = asked.num_rows
                yield pa.RecordBatch.from_arrays([pa.array([1] * k, pa.int32()), pa.nulls(k, pa.int64()), asked.column(0), pa.nulls(k, batch.column(0).type), *(pa.nulls(k, t) for t in (pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64())), asked.column(1), asked.column(2)], names)

    kind = dict(docs.dtypes)[key]
    done = materialise(rows.mapInArrow(lean(run), f"kind int, row long, part long, key {kind}, held_out boolean, n_tokens long, n_known long, base_score double, score double, words binary, rows binary"), "scores", ("kind",))

    def answer(frame: pd.DataFrame) -> pd.DataFrame:
        table, asked = frame[frame["rows"].isna()], frame[frame["rows"].notna()]
        words, counts = _joined(table, "words", np.uint64), _joined(table, "counts", np.int64)
        h, owner = _joined(asked, "words", np.uint64), _joined(asked, "rows", np.int64)
        at = np.minimum(np.searchsorted(words, h), max(0, len(words) - 1))
        c = np.where(words[at] == h, counts[at], 0) if len(words) else np.zeros(len(h), dtype=np.int64)
        rows, back = np.unique(owner, return_inverse=True)
        logs, known = np.bincount(back, weights=np.log10(c + 0.5), minlength=len(rows)), np.bincount(back, weights=c > 0, minlength=len(rows)).astype(np.int64)
        packed = _packed(rows >> 36, [rows, logs, known], ["task", "rows", "logs", "known"])
        return packed.to_pandas()

    asked = done.where("kind = 1").select("part", "words", F.lit(None).cast("binary").alias("counts"), "rows")
    table = counted.select("part", "words", "counts", F.lit(None).cast("binary").alias("rows"))
    answers = asked.unionByName(table).groupBy("part").applyInPandas(answer, "task long, rows binary, logs binary, known binary")

    def gather(frame: pd.DataFrame) -> pd.DataFrame:
        rows, back = np.unique(_joined(frame, "rows", np.int64), return_inverse=True)
        return pd.DataFrame({"row": rows, "logs": np.bincount(back, weights=_joined(frame, "logs", np.float64), minlength=len(rows)), "known": np.bincount(back, weights=_joined(frame, "known", np.int64), minlength=len(rows)).astype(np.int64)})

    rare = answers.groupBy("task").applyInPandas(gather, "row long, logs double, known long")
    both = done.where("kind = 0").join(rare, "row", "left")
    more = F.coalesce("logs", F.lit(0.0))
    return both.select(
        F.col("key").alias(key), "held_out", "n_tokens", (F.col("n_known") + F.coalesce("known", F.lit(0))).alias("n_known"), F.lit(model.train_tokens).cast("long").alias("train_tokens"),
        (F.col("base_score") + more).alias("base_score"), (F.col("score") + more).alias("score"),
    )
