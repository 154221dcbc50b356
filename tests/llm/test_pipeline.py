import hashlib

import numpy as np

import corpus_pipeline
from evenbatch.llm.pieces import PieceModel
from evenbatch.llm.queries import vocabulary

from .test_decontaminate import brute as leaks
from .test_jaccard import brute as groups


def test_stages_against_plain_versions(spark, sf):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    rows = [(k, t) for k, t in rows if t and any(map(str.isalpha, t))]
    first = {k for k, _, c in groups(rows) if k == c}
    kept = [(k, t) for k, t in rows if k in first and not leaks(t, items)[-1]]
    spm = PieceModel(vocabulary("piece_bpe_32k.model"))
    want = []
    for k, t in kept:
        ids = np.array([1, *spm.library.encode(t), 2], dtype="<u4")
        want.append((k, len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()))
    assert sorted(map(tuple, corpus_pipeline.run(spark, sf).collect())) == sorted(want)


def test_stages_keep_the_columns_of_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    odd = docs.limit(3).selectExpr("doc_id + 100000 AS doc_id", "CAST(NULL AS STRING) AS text", "lang", "source", "n_chars")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs.unionByName(odd), sf)
        assert out.columns == docs.columns and 0 < out.count() <= 203


def test_stages_take_empty_tables_repeated_rows_and_clashing_names(spark, sf):
    said = "the cat sat on the mat and looked at the dog that was there all day long "
    rows = [(1, said, "en", "rep", 1, "a"), (1, said, "en", "rep", 1, "a"), (2, said, "en", "x", 1, "b"), (3, "quite another text about ships and the sea at night", "en", "x", 1, "c"), (3, "quite another text about ships and the sea at night, again and again and again", "en", "x", 1, "c"), (4, None, "en", "x", 1, None), (None, said, None, "x", 1, "d"), (5, "", "en", None, None, None), (5, "", "en", None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, print string").withColumnRenamed("n_chars", "gram")
    stages = dict(corpus_pipeline.STAGES)
    one = stages["language"](spark, docs, sf)
    assert one.columns == docs.columns and sorted((r.doc_id or 0, r.print) for r in one.collect()) == [(0, "d"), (1, "a"), (1, "a"), (2, "b"), (3, "c"), (3, "c")]
    two = stages["near_duplicates"](spark, docs, sf)
    assert two.columns == docs.columns and sorted((r.doc_id or 0, r.print) for r in two.collect() if r.text) == [(0, "d"), (1, "a"), (3, "c")] and two.count() == 6
    three = stages["decontamination"](spark, docs, sf)
    assert three.columns == docs.columns and three.count() == len(rows)
    four = stages["encoding"](spark, docs, sf)
    assert four.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] and four.count() == len(rows)
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), sf).count() == 0, name


def test_language_stage_against_a_plain_rule(spark, sf):
    """What has a letter is in some learned language; what has none goes."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r.doc_id for r in corpus_pipeline.identify_language(spark, docs, sf).collect()}
    assert kept == {r.doc_id for r in docs.collect() if r.text and any(map(str.isalpha, r.text))}
