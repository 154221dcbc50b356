import random

import numpy as np
import pytest

from evenbatch.llm import jaccard
from evenbatch.llm.components import components


def shingles(text):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").split()
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute(rows):
    sets, top = {k: shingles(t) for k, t in rows}, {k: k for k, _ in rows}

    def root(x):
        while top[x] != x:
            x = top[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                top[y] = x
    return sorted((k, len(sets[k]), root(k)) for k in sets)


def corpus(seed, n):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(300)]
    passage = " ".join(rng.choices(vocabulary, k=40))
    bases = [" ".join(rng.choices(vocabulary, k=rng.choice([1, 3, 6, 30, 60]))) for _ in range(6)] + [passage]
    rows = []
    for i in range(n):
        words = rng.choice(bases).split()
        for _ in range(rng.choice([0, 0, 1, 2, 4])):
            words[rng.randrange(len(words))] = rng.choice(vocabulary)
        text = " ".join(words) + (" " + " ".join(rng.choices(vocabulary, k=rng.choice([2, 8, 12]))) if rng.random() < 0.5 else "")
        rows.append((i * 7 % 1000, text.upper() if i % 9 == 0 else text))
    return rows + [(2000, None), (2001, ""), (2002, " \n"), (2003, "one"), (2004, "One"), (2005, "one two three four"), (2006, "x" * 3000 + " y" * 8)]


@pytest.mark.parametrize("seed,few,hot,partners", [(1, 24, 200_000, 128), (3, 2, 3, 2)])
def test_against_brute_force(spark, monkeypatch, seed, few, hot, partners):
    for name, value in (("FEW", few), ("HOT", hot), ("PARTNERS", partners), ("PART_SHINGLES", 400), ("FLUSH_SHINGLES", 300)):
        monkeypatch.setattr(jaccard, name, value)
    rows = corpus(seed, 110)
    frame = spark.createDataFrame([(k, t, 1) for k, t in rows], "doc_id long, text string, component_id int").repartition(3)
    got = jaccard.link(frame)
    assert sorted(map(tuple, got.select("doc_id", "n_shingles", "component_id").collect())) == brute(rows)
    kept = {r.doc_id for r in jaccard.keep_first(frame).collect()}
    assert kept == {k for k, _, c in brute(rows) if k == c}


def test_empty_null_and_repeated_rows(spark):
    assert jaccard.link(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    rows = [(None, "a b c"), (1, "a b c"), (1, "a b c"), (0, "a b c"), (5, None)]
    got = sorted(map(tuple, jaccard.link(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=repr)
    assert got == sorted([(None, 1, None), (1, 1, 0), (1, 1, 0), (0, 1, 0), (5, 0, 5)], key=repr)


@pytest.mark.parametrize("first", [0, 1])
def test_rows_of_an_id_with_different_texts_are_one_node(spark, first):
    a, b = (" ".join(f"{x}{i}" for i in range(40)) for x in "ab")
    both = [a, b]
    rows = [(7, both[first]), (7, both[1 - first]), (3, a + " more"), (9, b + " more"), (8, "c"), (7, None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    assert sorted((r.doc_id, r.component_id) for r in jaccard.link(frame).collect()) == [(3, 3), (7, 3), (7, 3), (7, 3), (8, 8), (9, 3)]


def test_trie_finds_what_pairs_find():
    rng = np.random.default_rng(4)
    sets = [np.unique(rng.integers(0, 60, rng.integers(1, 40)).astype(np.uint64)) for _ in range(80)]
    trie = jaccard.Trie(list(enumerate(sets)))
    for probe in sets:
        want = {(i, len(np.intersect1d(probe, s))) for i, s in enumerate(sets) if 4 * len(np.intersect1d(probe, s)) >= 3 * len(np.union1d(probe, s))}
        assert set(trie.join(probe)) == want


def test_components_of_a_long_path(spark):
    n = 300
    edges = spark.range(n - 1).selectExpr("id + 1 AS a", "id AS b")
    assert {r.component for r in components(edges).collect()} == {0}


@pytest.mark.parametrize("order", ["valley", "shuffled"])
def test_components_of_chains_in_any_order_of_ids(spark, order):
    n = 200
    ids = [*range(1, n, 2), *reversed(range(0, n, 2))]
    if order == "shuffled":
        random.Random(5).shuffle(ids)
    edges = spark.createDataFrame(list(zip(ids, ids[1:])), "a long, b long")
    assert sorted(map(tuple, components(edges).collect())) == [(i, 0) for i in range(n)]
