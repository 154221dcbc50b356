import hashlib
import random

import numpy as np
import pytest

from evenbatch.llm.pieces import PieceModel, encode_documents
from evenbatch.llm.queries import vocabulary


@pytest.fixture(scope="module")
def spm():
    return PieceModel(vocabulary("piece_bpe_32k.model"))


def test_ids_and_text_equal_the_library(spm):
    rng = random.Random(3)
    parts = ["a", "b", "▁", " ", "  ", "\n", "é", "the", "<s>", "\x00", "日本", "\t", "ing", " t", "😀", "\r\n", "\xa0", ".", "'s", "word,", "x.y", "z" * 40]
    texts = ["".join(rng.choices(parts, k=rng.randint(0, 14))) for _ in range(3000)] + ["", " ", "a" * 5000]
    for text, ids in zip(texts, spm.encode_many(texts)):
        ids = np.frombuffer(ids, dtype="<u4")
        assert ids.tolist() == spm.library.encode(text)
        assert spm.decode(ids) == spm.library.decode(ids.tolist())
        assert spm.merge("▁" + text.replace(" ", "▁")) == ids.tolist() or not text


def test_disagreement_is_noticed(spm):
    with pytest.raises(ValueError):
        spm.check(["▁the"], [b"\1\0\0\0"])


def test_frame(spark, spm):
    rows = [(1, "Hello  world", 0), (2, None, 0), (3, "", 0), (1, "Hello  world", 0), (None, "x", 0)]
    got = sorted(((r.doc_id or 0), r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in encode_documents(spark.createDataFrame(rows, "doc_id long, text string, n_tokens int"), vocabulary("piece_bpe_32k.model")).collect())
    want = []
    for k, t, _ in rows:
        ids = [1, *spm.library.encode(t or ""), 2]
        want.append((k or 0, len(ids), hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert got == sorted(want)
    assert encode_documents(spark.createDataFrame([], "doc_id long, text string"), vocabulary("piece_bpe_32k.model")).count() == 0
