"""The queries of this subpackage and the SQL that says the same, where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import brown, chat, decontaminate, html, jaccard, langid, media, pieces, sharding, tokenfile
from .storage import table

SHARDS = 40


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return html.extract_pages(pages, html.weights_from(pages))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return langid.predict(docs, langid.learn(docs.where(~langid.held_out())))


def op3_media_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return media.fetch(docs, media.store(docs))


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_items(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.read_segments(tokenfile.write_segments(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), end_id=1))


def op6_jump_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"), SHARDS)


def op7_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = chat.log_of(chat.with_probe(table(spark, sf_dir, "conversations")))
    return chat.digest(chat.parse(chat.render(chat.fold_events(events))))


def op8_class_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return brown.score(table(spark, sf_dir, "documents"))


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.encode_documents(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))


def op10_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.link(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_html_extraction, op2_language_id, op3_media_chunks, op4_decontamination, op5_token_output, op6_jump_sharding, op7_chat_formatting, op8_class_lm, op9_sentencepiece, op10_jaccard_join)}

ORACLES: dict[str, str] = {
    "op10_jaccard_join": jaccard.ORACLE,
    "op4_decontamination": decontaminate.ORACLE,
    "op7_chat_formatting": r"""
        WITH rows AS (
            SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
            UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
        texts AS (
            SELECT conv_id, count(*) AS n_turns,
                string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS said,
                coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '') AS loss,
                sum(length(text) + length(role) + 3 * 8 + length(regexp_replace(text || role, '[^\\<\[]', '', 'g'))) AS formatted
            FROM rows GROUP BY conv_id)
        SELECT conv_id, n_turns, sha256(said) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars, sha256(loss) AS loss_sha256, CAST(formatted AS BIGINT) AS formatted_chars FROM texts""",
}
