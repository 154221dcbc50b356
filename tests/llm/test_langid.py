import math
import re
from collections import Counter

import pytest

from evenbatch.llm import langid
from evenbatch.llm.queries import op2_language_id


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    truth = {r.doc_id: (r.lang, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = op2_language_id(spark, sf).collect()
    assert len(got) == len(truth) and all(0 <= r.score <= 1 for r in got)
    out = [r for r in got if r.held_out and any(map(str.isalpha, truth[r.doc_id][1]))]
    assert 100 < len(out) and sum(r.lang_pred == truth[r.doc_id][0] for r in out) / len(out) > 0.97


def test_words_then_shorter_grams(spark):
    rows = [(i, "the cat sat on the mat", "en", 0) for i in range(5)] + [(i, "der hund lief über die wiese", "de", 0) for i in range(5)] + [(9, None, "en", 0), (9, "x", None, 0)]
    model = langid.learn(spark.createDataFrame(rows, "doc_id long, text string, lang string, score int"))
    assert model.languages == ["de", "en"] and "the" in model.words and "über" in model.words
    assert model.predict("The Mat")[0] == "en" and model.predict("Überwiesen")[0] == "de" and model.predict("cats")[0] == "en"
    for nothing in (None, "", " 12 ²²!"):
        assert model.predict(nothing) == ("und", 0.0)
    assert model.predict("the cat " * 100_000)[0] == "en"
    docs = spark.createDataFrame([(1, "the mat", "zz", 5), (None, None, None, 5), (1, "...", "en", 5)], "doc_id long, text string, lang string, lang_pred int")
    assert {(r.lang_pred, r.held_out) for r in langid.predict(docs, model).collect()} == {("en", langid_held(1)), ("und", True), ("und", langid_held(1))}
    assert [tuple(r) for r in langid.keep_identified(docs, model).collect()] == [(1, "the mat", "zz", 5)]


def langid_held(key):
    import zlib

    return zlib.crc32(str(key).encode()) % 5 == 0


def test_nothing_to_learn_from(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, lang string")
    model = langid.learn(empty)
    assert model.predict("words") == ("und", 0.0) and langid.predict(empty, model).count() == 0


def test_long_words_count_whole():
    model = langid.Model([("en", 0, "the", 9), ("fr", 0, "le", 9), *((lang, 1, c, 50) for lang, c in (("en", "w"), ("fr", "q")))])
    assert model.predict("w" * 70 + "q" * 400)[0] == "fr" and model.predict("q" * 70 + "w" * 400)[0] == "en"


def test_rare_languages_are_learned_from_whole():
    got = langid.shares({"a": 1_000_000, "b": 300, "c": 50_000, "d": 1}, 20_000)
    assert got["b"] == got["d"] == 1 and abs(got["a"] * 1_000_000 - got["c"] * 50_000) <= 1
    assert sum(got[k] * n for k, n in {"a": 1_000_000, "b": 300, "c": 50_000, "d": 1}.items()) <= 20_000
    assert langid.shares({"a": 5}, 20_000) == {"a": 1} and langid.shares({}, 5) == {}


def test_scores_against_plain_dictionaries(spark):
    """Every word's score by dictionaries of counts, without the vector table and its memory."""
    rows = [(i, t, lang) for i, (t, lang) in enumerate([("the cat sat on the mat", "en"), ("the dog and the cat", "en"), ("le chat est sur le tapis", "fr"), ("le chien et le chat", "fr"), ("der hund und die katze", "de")] * 3)]
    model = langid.learn(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    counts = {}
    for _, t, lang in rows:
        for w in t.split():
            counts.setdefault((lang, 0), Counter())[w] += 1
            m = f"<{w}>"
            for n in range(1, 5):
                counts.setdefault((lang, n), Counter()).update(m[i : i + n] for i in range(len(m) - n + 1))
    langs = ["de", "en", "fr"]

    def log(n, g, lang):
        known = {x for k in langs for x in counts[k, n]}
        return math.log((counts[lang, n][g] + 0.5) / (sum(counts[lang, n].values()) + 0.5 * (len(known) + 1))) if g in known else None

    def word(w, lang):
        if (x := log(0, w, lang)) is not None:
            return x
        m, total = f"<{w}>", 0.0
        for end in range(2, len(m) + 1):
            for n in range(min(4, end), 0, -1):
                if (x := log(n, m[end - n : end], lang)) is not None:
                    total += x + math.log(0.4) * (4 - n)
                    break
        return total / (len(m) - 1) * min(2.0, (len(m) - 1) / 3)

    for text in ("the mat", "le tapis rouge", "die katzen und hunde", "zzz", "The CAT, et le chien!"):
        want = [sum(word(w, lang) for w in re.findall("[a-z]+", text.lower())) for lang in langs]
        best = max(range(3), key=lambda i: want[i])
        said, score = model.predict(text)
        assert said == langs[best] and score == pytest.approx(1 / sum(math.exp(x - want[best]) for x in want))


def test_unknown_words_are_scored_together(monkeypatch):
    """Many new words cost a few array operations, and give what each gives alone, also when the memory is emptied."""
    grams = ("a", "b", "ab", "<a", "b>", "abc", "bcab", "²", "<", ">")
    model = langid.Model([(lang, len(g) if g != "the" else 0, g, c) for lang, more in (("en", 3), ("fr", 1)) for c, g in enumerate(("the", *grams), more)])
    words = ["".join("abcx²"[(i // 5**k) % 5] for k in range(1 + i % 6)) for i in range(2_000)] + ["the", "²²"]
    alone = []
    for w in words:
        model._forget()
        model.remember([w])
        alone.append(model.table[model.memory[w]])
    model._forget()
    model.remember(words)
    assert all((model.table[model.memory[w]] == x).all() for w, x in zip(words, alone)) and model.memory["²²"] == 0
    calls = []
    monkeypatch.setattr(langid, "MEMORY_WORDS", 700)
    monkeypatch.setattr(langid.Model, "backoff", lambda self, part, real=langid.Model.backoff: calls.append(len(part)) or real(self, part))
    model._forget()
    got = [model.predict(" ".join(words[a : a + 500])) for a in range(0, len(words), 500)]
    assert len(calls) == 4 and len(model.memory) <= 1_200 and all(g[0] in ("en", "fr") for g in got)
    assert model.predict("²² ²") == ("und", 0.0)
