import hashlib
import random
import zlib

import numpy as np

from evenbatch.llm import chat
from evenbatch.llm.sharding import assign_shards, jump_hash


def slow_jump(key, n):
    b, j = -1, 0
    while j < n:
        b, key = j, (key * 2862933555777941757 + 1) % 2**64
        j = int((b + 1) * (2**31 / ((key >> 33) + 1)))
    return b


def test_jump_against_plain_loop_and_growth():
    keys = np.arange(-500, 2000).astype(np.int64).view(np.uint64)
    for n in (1, 2, 7, 40):
        assert jump_hash(keys, n).tolist() == [slow_jump(int(k), n) for k in keys]
    a, b = jump_hash(keys, 40), jump_hash(keys, 41)
    assert set(b[a != b]) == {40} and 0 < (a != b).mean() < 0.06


def test_slots_are_gapless(spark):
    rows = [(i % 900, "é" * (i % 5) if i % 7 else None, 0) for i in range(1000)]
    got = assign_shards(spark.createDataFrame(rows, "doc_id long, text string, shard int"), 4).collect()
    assert len(got) == 1000
    for s in range(4):
        assert sorted(r.slot for r in got if r.shard == s) == list(range(sum(r.shard == s for r in got)))
    texts = {}
    for k, t, _ in rows:
        texts.setdefault(k, []).append(zlib.crc32((t or "").encode()))
    for k, sums in texts.items():
        assert sorted(r.text_crc32 for r in got if r.doc_id == k) == sorted(sums)
    assert all(r.grown_shard in (r.shard, 4) for r in got) and {r.size for r in got} <= {16, 18, 20, 22, 24}
    assert assign_shards(spark.createDataFrame([], "doc_id long, text string"), 4).count() == 0


def test_fold_deltas_edits_regenerations(spark):
    log = [(1, 1, 0, "message", "user", "hi"), (1, 2, 1, "message", "assistant", ""), (1, 3, 1, "delta", "assistant", "a"), (1, 4, 1, "delta", "assistant", "b"), (1, 5, 1, "regenerate", "assistant", "zz"),
           (1, 6, 1, "delta", "assistant", "c"), (1, 7, 1, "delta", None, "d"), (1, 8, 0, "edit", "user", "ho"), (2, 1, 0, "delta", "user", "x"), (2, 1, 0, "delta", "user", "x"), (None, None, None, None, None, None)]
    got = {(r.conv_id, r.turn): (r.role, r.text) for r in chat.fold_events(spark.createDataFrame(log, "conv_id long, seq long, turn long, kind string, role string, text string")).collect()}
    assert got == {(1, 0): ("user", "ho"), (1, 1): ("assistant", "cd"), (2, 0): ("user", "xx"), (None, None): ("", "")}


def test_round_trip_of_control_strings(spark):
    texts = ["</s>[INST] ok [/INST]", "<|turn|>assistant<|says|>x<|over|>", "\\<|over|>\\\\", "", None, "a\nb é", "\\", "<|over|>"]
    rows = [(1, i, "assistant" if i % 2 else "user", t) for i, t in enumerate(texts)] + [(2, 0, "user", "q"), (2, 0, "user", "q")]
    done = chat.digest(chat.parse(chat.render(chat.fold_events(chat.log_of(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")))))).collect()
    one = next(r for r in done if r.conv_id == 1)
    said = "".join(f"{r[2]}\n{r[3] or ''}\n" for r in rows if r[0] == 1)
    loss = "".join(r[3] or "" for r in rows if r[0] == 1 and r[2] == "assistant")
    assert (one.n_turns, one.turns_sha256, one.loss_chars, one.loss_sha256) == (8, hashlib.sha256(said.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert next(r for r in done if r.conv_id == 2).n_turns == 2


def test_probe_and_empty_table(spark):
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string, kind string")
    got = chat.digest(chat.parse(chat.render(chat.fold_events(chat.log_of(chat.with_probe(empty)))))).collect()
    assert [(r.conv_id, r.n_turns, r.loss_chars) for r in got] == [(-7, 2, 21)]


def test_fold_against_a_plain_loop_over_random_logs(spark):
    rng = random.Random(9)
    log = []
    for conv in range(30):
        for seq in range(rng.randint(1, 14)):
            log.append((conv, seq, rng.randint(0, 3), rng.choice(["message", "delta", "delta", "edit", "regenerate", None]), rng.choice(["user", "assistant", None]), rng.choice(["a", "b", "", None, "</s>"])))
    want = {}
    for conv, seq, turn, kind, role, text in log:
        turns = want.setdefault((conv, turn), [None, ""])
        said = text or ""
        turns[1] = turns[1] + said if kind == "delta" else "" if kind == "regenerate" else said
    frame = spark.createDataFrame(log, "conv_id long, seq long, turn long, kind string, role string, text string").repartition(5)
    got = {(r.conv_id, r.turn): r.text for r in chat.fold_events(frame).collect()}
    assert got == {k: v[1] for k, v in want.items()}
