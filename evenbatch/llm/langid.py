"""Language identification, words first.

A word known from training scores its log frequency in each language. For an unknown word the score backs off to
character n-grams of the marked word, from the longest to single characters: at each place the longest known n-gram
ending there counts, at a penalty a step. A text's score for a language is the sum over its words.

Words are runs of letters, lower-cased. Text without a letter, and null, is `und` with score 0, as is every text if
nothing was there to learn from. Of equal languages the first by name is taken. Training reads at most about
TRAIN_DOCS labelled rows, as many of each language where there are enough, chosen by a hash of their key and text;
prediction reads text only. Rows that repeat are predicted each.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import send
from .textkernel import lean, text_batches

#: Bounds of what is learned: labelled rows read, words and n-grams of each length kept of a language.
TRAIN_DOCS = 20_000
KEEP_WORDS = 20_000
KEEP_GRAMS = 6_000
LONGEST = 4
BACKOFF = math.log(0.4)
UNKNOWN = "und"
#: Remembered words of a Python worker at most, some 150 bytes each.
MEMORY_WORDS = 200_000

WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def grams_of(word: str) -> Iterator[str]:
    marked = f"<{word}>"
    for n in range(1, LONGEST + 1):
        for i in range(len(marked) - n + 1):
            yield marked[i : i + n]


class Model:
    """Log frequencies: of words, and of n-grams by length, each a row over the languages."""

    def __init__(self, rows: list[tuple[str, int, str, int]]):
        """rows: (language, n, text, count); n is 0 for words."""
        self.languages = sorted({r[0] for r in rows})
        at = {x: i for i, x in enumerate(self.languages)}
        counts: dict[int, dict[str, np.ndarray]] = defaultdict(lambda: defaultdict(lambda: np.zeros(len(at))))
        for lang, n, text, c in rows:
            counts[n][text][at[lang]] += c
        self.words: dict[str, int] = {}
        self.grams: dict[str, int] = {}
        kept: dict[bool, list[np.ndarray]] = {True: [np.zeros((0, len(at)))], False: [np.zeros((0, len(at)))]}
        for n, seen in counts.items():
            total = sum(seen.values()) + 0.5 * (len(seen) + 1)
            names = self.grams if n else self.words
            names.update(zip(seen, range(len(names), len(names) + len(seen))))
            kept[n > 0].append(np.log((np.array(list(seen.values())) + 0.5) / total) + (BACKOFF * (LONGEST - n) if n else 0.0))
        self.word_rows, self.gram_rows = np.concatenate(kept[False]), np.concatenate(kept[True])
        self._forget()

    def _forget(self) -> None:
        """Empty the memory of words; row 0 is that of words without a letter."""
        self.memory: dict[str, int] = {}
        self.table, self.used = np.zeros((1024, len(self.languages))), 1

    def places(self, word: str) -> list[int]:
        """The row of the longest known n-gram that ends at each place of the word, where there is one."""
        marked, find, out = f"<{word}>", self.grams.get, []
        for end in range(2, len(marked) + 1):
            for start in range(end - LONGEST if end > LONGEST else 0, end):
                found = find(marked[start:end])
                if found is not None:
                    out.append(found)
                    break
        return out

    def backoff(self, words: list[str]) -> np.ndarray:
        """For each word the mean over its places of the longest known n-gram there, weighed as two words at most."""
        found = [self.places(w) for w in words]
        ends = np.cumsum([0, *map(len, found)])
        lens = np.array([len(w) + 1 for w in words])
        sums = np.zeros((len(words), len(self.languages)))
        some = ends[1:] > ends[:-1]
        if some.any():
            sums[some] = np.add.reduceat(self.gram_rows[[i for f in found for i in f]], ends[:-1][some])
        return sums / lens[:, None] * np.minimum(2.0, lens / 3)[:, None]

    def remember(self, words: list[str]) -> None:
        """Give each of these words that has none yet a row of the table."""
        new = [w for w in dict.fromkeys(words) if w not in self.memory]
        lettered = [w for w in new if w.isalpha() or any(map(str.isalpha, w))]
        self.memory.update(dict.fromkeys(new, 0))
        self.memory.update(zip(lettered, range(self.used, self.used + len(lettered))))
        if self.used + len(lettered) > len(self.table):
            self.table = np.concatenate((self.table, np.zeros((self.used + len(lettered), len(self.languages)))))
        known = [w for w in lettered if w in self.words]
        self.table[[self.memory[w] for w in known]] = self.word_rows[[self.words[w] for w in known]]
        other = [w for w in lettered if w not in self.words]
        for a in range(0, len(other), 5_000):
            part = other[a : a + 5_000]
            self.table[[self.memory[w] for w in part]] = self.backoff(part)
        self.used += len(lettered)

    def predict(self, text: str | None) -> tuple[str, float]:
        words = words_of(text) if text and self.languages else []
        score, lettered = np.zeros(len(self.languages)), False
        for a in range(0, len(words), 50_000):
            part = words[a : a + 50_000]
            rows = list(map(self.memory.get, part))
            if None in rows:
                if len(self.memory) + len(part) > MEMORY_WORDS:
                    self._forget()
                self.remember(part)
                rows = list(map(self.memory.get, part))
            lettered = lettered or any(rows)
            score += self.table[np.fromiter(rows, np.intp, len(rows))].sum(0)
        if not lettered:
            return UNKNOWN, 0.0
        best = int(score.argmax())
        return self.languages[best], float(1 / np.exp(np.minimum(score - score[best], 0)).sum())


def shares(there: dict[str, int], budget: int) -> dict[str, float]:
    """The share of each language's rows that is learned from: the budget is dealt evenly, and what languages with few
    rows leave of it goes to the others, so that a rare one is learned from whole."""
    out, left = {}, len(there)
    for lang, n in sorted(there.items(), key=lambda x: (x[1], x[0])):
        taken = min(n, budget // left)
        out[lang], budget, left = taken / n, budget - taken, left - 1
    return out


def learn(labelled: DataFrame, key: str = "doc_id", text: str = "text", label: str = "lang") -> Model:
    """A model from rows with text and label."""
    rows = labelled.select(F.col(key).alias("key"), F.col(text).alias("text"), F.col(label).alias("lang")).where("text IS NOT NULL AND lang IS NOT NULL")
    there = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}  # one row a language
    part = shares(there, TRAIN_DOCS)
    if any(x < 1 for x in part.values()):
        limit = F.create_map(*[F.lit(x) for lang, share in part.items() for x in (lang, int(share * (1 << 30)))])
        rows = rows.where(F.pmod(F.xxhash64("key", "text"), F.lit(1 << 30)) < F.element_at(limit, F.col("lang")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words: dict[str, Counter] = defaultdict(Counter)
        for batch in batches:
            for raw, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                words[lang].update(words_of(raw))
        for lang, seen in words.items():
            grams: list[Counter] = [Counter() for _ in range(LONGEST + 1)]
            for word, c in seen.items():
                for g in grams_of(word):
                    grams[len(g)][g] += c
            for n, counter in enumerate([seen, *grams[1:]]):
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(counter), pa.string()), pa.array([n] * len(counter), pa.int32()), pa.array(list(counter), pa.string()), pa.array(list(counter.values()), pa.int64())], ["lang", "n", "gram", "seen"])

    counted = rows.select("text", "lang").mapInArrow(lean(run), "lang string, n int, gram string, seen long").groupBy("lang", "n", "gram").agg(F.sum("seen").alias("seen"))
    place = F.row_number().over(Window.partitionBy("lang", "n").orderBy(F.desc("seen"), "gram"))
    kept = counted.withColumn("place", place).where(F.col("place") <= F.when(F.col("n") == 0, KEEP_WORDS).otherwise(KEEP_GRAMS))
    return Model([(r["lang"], r["n"], r["gram"], r["seen"]) for r in kept.select("lang", "n", "gram", "seen").toLocalIterator()])


def held_out(key: str = "doc_id"):
    return F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def predict(docs: DataFrame, model: Model, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, held_out, lang_pred, score of every row."""
    shared = send(docs.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_batches(batches):
            got = [shared.value.predict(t.decode() if t else None) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], [key, "held_out", "lang_pred", "score"])

    return docs.select(key, held_out(key).alias("held_out"), F.col(text).alias("text")).mapInArrow(lean(run), f"{key} {dict(docs.dtypes)[key]}, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of docs, with all their columns, that are in some learned language."""
    shared = send(docs.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_batches(batches):
            yield batch.filter(pa.array([shared.value.predict(t.decode() if t else None)[0] != UNKNOWN for t in texts], pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
