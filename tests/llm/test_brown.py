import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from evenbatch.llm import brown


def base_of(rows):
    toks = lambda t: re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")) + [None]
    held = {k: zlib.crc32(str(k).encode()) % 5 == 1 for k, _ in rows}
    c = Counter(x for k, t in rows if not held[k] for x in toks(t))
    n, v = sum(c.values()), len(c)
    return [(k, held[k], len(toks(t)), sum(c[x] > 0 for x in toks(t)), n, sum(math.log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in toks(t))) for k, t in rows]


@pytest.mark.parametrize("keep", [300_000, 5])
def test_base_counts_are_exact(spark, sf, monkeypatch, keep):
    monkeypatch.setattr(brown, "KEEP", keep)
    monkeypatch.setattr(brown, "PART_BYTES", 40_000)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()][:60] + [(5001, None), (5002, ""), (5003, "zz " * 500)]
    got = {r.doc_id: r for r in brown.score(spark.createDataFrame([(k, t, 0.0) for k, t in rows], "doc_id long, text string, score double")).collect()}
    assert len(got) == len(rows)
    for k, held, n, known, total, base in base_of(rows):
        r = got[k]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held, n, known, total)
        assert r.base_score == pytest.approx(base, rel=1e-9)


def test_beats_the_base_on_held_out_texts(spark):
    got = [r for r in brown.score(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).collect() if r.held_out]
    assert len(got) > 100 and sum(r.score for r in got) > sum(r.base_score for r in got) and all(r.score < 0 for r in got)


def test_probabilities_sum_to_one(spark):
    docs = spark.createDataFrame([(i, "a b. c, é a b a x y z") for i in range(20)], "doc_id long, text string")
    model, _ = brown.train(docs.select("text"), 2)
    assert np.allclose((10**model.transition).sum(1), 1)
    emitted = np.zeros(len(model.emission_total))
    np.add.at(emitted, model.kind, model.counts + 0.5)
    assert (emitted <= model.emission_total + 1e-9).all()


def test_exchange_separates_two_languages():
    rng = np.random.default_rng(0)
    table = np.zeros((20, 20))
    for _ in range(4000):
        side = rng.integers(2) * 10
        table[side + rng.integers(10), side + rng.integers(10)] += 1
    of = brown.exchange(table, 20, 2, 10)
    assert len(set(of[:10])) == 1 and len(set(of[10:])) == 1 and of[0] != of[10]


def test_empty_table(spark):
    assert brown.score(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_no_more_words_are_kept_than_fit(spark, monkeypatch):
    monkeypatch.setattr(brown, "KEEP", 300)
    counts = np.concatenate((np.full(10, 5), np.full(400, 2), np.full(100, 1)))
    row = (0, np.arange(len(counts), dtype=np.uint64).tobytes(), counts.astype(np.int64).tobytes(), bytes(len(counts)))
    counted = spark.createDataFrame([tuple(bytearray(x) if isinstance(x, bytes) else x for x in row)], "part long, words binary, counts binary, shapes binary")
    model = brown._table_of(counted, 3)
    assert len(model.known) == 10 and model.train_tokens == 50 + 800 + 100 + 3 and model.vocabulary == 511


def test_words_join_the_class_of_like_words():
    """Two free classes; a word of the third class that stands where the first one's words stand joins them."""
    table = np.array([[0.0, 90, 5], [90, 0, 5], [5, 5, 0]])
    got = brown.better_classes(np.array([0, 0, 1, 1]), np.array([0, 1, 0, 1]), np.array([1, 1, 0, 0]), np.array([5, 5, 5, 5]), np.array([2, 2]), table, 2)
    assert got.tolist() == [0, 1]


def test_scores_against_a_plain_sum(spark, monkeypatch):
    """The score column, token by token, from the trained tables; rare words come by the shuffle."""
    monkeypatch.setattr(brown, "KEEP", 12)
    rows = [(i, " ".join(f"w{(i * 7 + j * j) % (9 + i)}{',' if j % 4 == 0 else ''}" for j in range(i % 13))) for i in range(60)] + [(101, None), (102, "unseen wörter.")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    model, _ = brown.train(docs.where("crc32(cast(cast(doc_id as string) as binary)) % 5 <> 1").select("text"), 1)
    counts = Counter(w for k, t in rows if zlib.crc32(str(k).encode()) % 5 != 1 for w in (t or "").split())
    got = {r.doc_id: r.score for r in brown.score(docs).collect()}
    for key, text in rows:
        total, before = 0.0, model.classes - 1
        for w in (text or "").split():
            h = brown.Words([w.encode()]).hashes()[0]
            known = np.flatnonzero(model.known == h)
            shape = (0 if w[-1] == "." else 1 if w[-1] == "," else 2) + 3 * (not w.isascii())
            c = model.kind[known[0]] if len(known) else model.free + shape
            total += model.transition[before, c] + math.log10(counts[w] + 0.5) - math.log10(model.emission_total[c])
            before = c
        total += model.transition[before, model.classes - 1]
        assert got[key] == pytest.approx(total, rel=1e-9)
