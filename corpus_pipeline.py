"""From raw documents to token ids: language identification, near duplicates, benchmark leaks, encoding.

Every stage works on all rows its predecessor kept. Null and empty texts are not in any language and go with the first
stage; further columns are kept by all stages but the last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from evenbatch.llm import decontaminate, jaccard, langid, pieces
from evenbatch.llm.queries import vocabulary
from evenbatch.llm.storage import materialise, release, table


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in some language that the labelled rows teach; the others go."""
    return langid.keep_identified(docs, langid.learn(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that links of similarity 0.75 and more hold together."""
    release()  # the stage before has been written
    return jaccard.keep_first(docs)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no window of a benchmark item occurs."""
    release()
    return decontaminate.keep_clean(docs, table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded text of each document left."""
    release()
    return pieces.encode_documents(docs, vocabulary("piece_bpe_32k.model"))


STAGES = [("language", identify_language), ("near_duplicates", drop_near_duplicates), ("decontamination", drop_benchmark_leaks), ("encoding", encode)]

#: Language models and merges are not SQL; tests/llm/test_pipeline.py holds the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
