import hashlib
import random
import re

import pytest

from evenbatch.llm import decontaminate

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(t):
    return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))


def brute(text, items):
    w, hit, found = words(text), set(), set()
    for item, t in items:
        x = words(t)
        for s in range(max(1, len(x) - 9) if x else 0):
            g = x[s : s + 10]
            for p in range(len(w) - len(g) + 1):
                if w[p : p + len(g)] == g:
                    hit.update(range(p, p + len(g)))
                    found.add("null" if item is None else str(item))
    return len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)


@pytest.mark.parametrize("small", [0, 10**9])
def test_against_brute_force(spark, monkeypatch, small):
    monkeypatch.setattr(decontaminate, "BROADCAST_WINDOWS", small)
    rng = random.Random(7)
    said = lambda n: " ".join(rng.choice(["a", "B", "é", "word", "10", "longerword"]) for _ in range(n))
    items = [(i, said(rng.choice([1, 2, 4, 6, 10, 13]))) for i in range(14)] + [(None, "null item here"), (20, None), (21, " . "), (3, "again"), (22, "a b é word"), (23, "a b é word")]
    docs = [(i, said(rng.randint(0, 30)) + ("! " + items[i % 14][1].replace(" ", " - ") if i % 3 else "")) for i in range(120)] + [(None, None), (5, ""), (5, "NULL  item, here"), (5, "a b é word " * 3)]
    frame = spark.createDataFrame([(k, t, 0) for k, t in docs], "doc_id long, text string, n_hit int")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.find_items(frame, bench).collect()
    want = [(k, *brute(t, items)) for k, t in docs]
    order = lambda rows: sorted(map(tuple, rows), key=repr)
    assert order(got) == order(want)
    assert decontaminate.keep_clean(frame, bench).count() == sum(not w[-1] for w in want)


def test_empty_tables(spark):
    none, docs = spark.createDataFrame([], "item_id long, text string"), spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    assert [tuple(r)[1:4] for r in decontaminate.find_items(docs, none).collect()] == [(2, 0, 0)]
    assert decontaminate.find_items(docs.limit(0), docs.toDF("item_id", "text")).count() == 0
