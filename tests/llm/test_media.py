import hashlib
import random
import zlib

from evenbatch.llm.media import GEAR, LEAST, MOST, chunks_of, cuts, fetch, payload_of, store


def slow_cuts(payload):
    out, start, h = [], 0, 0
    for i, b in enumerate(payload):
        h = ((h << 1) + int(GEAR[b])) & 0xFFFFFFFF
        size = i + 1 - start
        if size == MOST or (size >= LEAST and h >> 22 == 0) or i + 1 == len(payload):
            out.append(i + 1)
            start = i + 1
    return out


def test_cuts_equal_a_plain_rolling_loop_and_follow_content():
    rng = random.Random(2)
    for n in (64, 640, 20_000, 70_000):
        data = bytes(rng.randrange(256) for _ in range(n))
        assert cuts(data) == slow_cuts(data) and b"".join(chunks_of(data)) == data
    assert cuts(bytes(40_000)) == slow_cuts(bytes(40_000))
    a = set(chunks_of(data))
    b = set(chunks_of(b"inserted" + data))
    assert len(a & b) > len(a) * 0.8


def test_round_trip(spark):
    rng = random.Random(3)
    part = ["".join(rng.choices("abcdefé ", k=3000)) for _ in range(4)]
    texts = [part[i % 4] + part[(i // 4) % 4] + (str(i) * 30 if i % 3 else "") for i in range(40)] + [None, "", "x" * 64, "x" * 65, "é" * 50_000] + [part[0]] * 5
    rows = [(i if i % 11 else None, t, 7) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_bytes int").repartition(3)
    got = fetch(docs, store(docs)).collect()

    def want(k, t):
        p = payload_of((t or "").encode())
        return k, len((t or "").encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:])

    key = lambda r: (r[0] or -1, *r[1:])
    assert sorted(((r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in got), key=key) == sorted((want(k, t) for k, t, _ in rows), key=key)
    assert len({(r.media_bytes, r.media_sha256, r.feature) for r in got if r.payload_sha256 == want(0, part[0])[3]}) == 1
    assert all(r.media_bytes > r.payload_bytes for r in got)


def test_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert fetch(docs, store(docs)).count() == 0
