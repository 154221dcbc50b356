import random
import zlib

import numpy as np
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from evenbatch.llm import tokenfile
from evenbatch.llm.queries import vocabulary
from evenbatch.llm.tokenfile import EliasFano, Segment, pack, read_segments, tokenizer, write_segments

PATH = vocabulary("word_bpe_49k.json")


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 1 << 40), max_size=300))
def test_elias_fano_round_trip_and_select(values):
    values = np.array(sorted(values), dtype=np.int64)
    coded, _ = EliasFano.read(EliasFano.of(values).write(), 0)
    assert coded.all().tolist() == values.tolist()
    assert [coded.select(i) for i in range(len(values))] == values.tolist()


def test_near_minimal_space():
    ends = np.cumsum(np.random.default_rng(1).integers(1, 1000, 20000))
    assert len(EliasFano.of(ends).write()) * 8 / 20000 < 2.3 + np.log2(ends[-1] / 20000)


def test_segment_with_null_and_negative_keys():
    s = Segment(pack([None, -5, -5, 7], np.array([1, 3, 3, 4]), np.array([9, 8, 7, 6], dtype="<u2").tobytes(), 2))
    assert s.keys() == [None, -5, -5, 7] and s.offsets(1) == (1, 3) and s.offsets(2) == (3, 3) and s.ids.tolist() == [9, 8, 7, 6]


def test_remembered_words_equal_the_library():
    rng = random.Random(5)
    words = tokenizer(PATH)
    parts = ["the", "The", "THE,", "don't", "it's.", "é", "É!", " ", "  ", "\n", "\t", "\x1c", "\xa0", "123", "a1b2", "日本", "<|endoftext|>", "x.", ",", "...", "ﬁ", "é", "́", "Σ", "İ", "'s", "-", "a-b;", "\r\n", "T\u0308", "h\u0331", "=", "\u0338", "×", "÷.", "…", ".%%%", "<|", "|>", "<|ENDOFTEXT|>"]
    for _ in range(3000):
        text = "".join(rng.choices(parts, k=rng.randint(0, 10)))
        assert words.encode(text) == words.plain(text), text


def test_frame(spark, monkeypatch):
    monkeypatch.setattr(tokenfile, "SEGMENT_IDS", 5)
    rows = [(i * 3 % 50, "Word, and\nmore  words " * (i % 4) if i % 6 else None, 0) for i in range(50)] + [(None, "x", 0), (3, "twice", 0)]
    got = read_segments(write_segments(spark.createDataFrame(rows, "doc_id long, text string, start int"), PATH, 1)).collect()
    words, at, want = tokenizer(PATH), 0, []
    dealt = lambda t: 42 if t is None else int(np.uint64(xxhash.xxh64(t.encode(), seed=42).intdigest()).astype(np.int64))
    for k, t, _ in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, dealt(r[1]))):
        ids = np.concatenate((np.frombuffer(words.plain(t or ""), words.kind), [1])).astype("<u4")
        want.append((k, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert sorted(((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in got), key=lambda r: r[1]) == want
    assert read_segments(write_segments(spark.createDataFrame([], "doc_id long, text string"), PATH, 1)).count() == 0
