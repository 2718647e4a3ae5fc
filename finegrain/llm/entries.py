"""Queries of this subpackage by name, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from finegrain.llm import contamination, exact_dedup, licences, lm, near_dedup, pieces, quality, sharding, surrogates, token_files
from finegrain.sources.tables import load


def tokenizer_file(name: str) -> str:
    """Where the public tokenizers keep a vocabulary file."""
    import public_tokenizers

    return str(public_tokenizers.path(name))


def piece_model() -> bytes:
    """The bytes of the public piece model."""
    with open(tokenizer_file("piece_bpe_32k.model"), "rb") as source:
        return source.read()


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.piece_digests(load(spark, sf_dir, "documents", ["doc_id", "text"]), piece_model())


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    scanned = licences.scan_licences(load(spark, sf_dir, "documents", ["doc_id", "text"]))
    return scanned.select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")


def op3_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(load(spark, sf_dir, "documents", ["doc_id", "text"]))


def op4_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    changed = surrogates.with_surrogates(load(spark, sf_dir, "documents", ["doc_id", "text"]))
    return changed.select("doc_id", "text", "n_entities", "entity_kinds")


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    marked = exact_dedup.exact_dedup_digest(load(spark, sf_dir, "documents", ["doc_id", "text"]))
    return marked.select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op6_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    digests = token_files.token_digests(spark, load(spark, sf_dir, "documents", ["doc_id", "text"]), tokenizer_file("word_bpe_49k.json"))
    return digests.select("doc_id", "start", "n_tokens", "ids_crc32")


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_scores(load(spark, sf_dir, "documents", ["doc_id", "text"]), load(spark, sf_dir, "labels"))


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.sharded_documents(load(spark, sf_dir, "documents", ["doc_id", "text"]))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination.contaminated_documents(load(spark, sf_dir, "documents", ["doc_id", "text"]), load(spark, sf_dir, "benchmark", ["item_id", "text"]))


def op10_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score_documents(load(spark, sf_dir, "documents", ["doc_id", "text"]))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_sentencepiece": op1_sentencepiece,
        "op2_license_scan": op2_license_scan,
        "op3_near_dedup": op3_near_dedup,
        "op4_surrogates": op4_surrogates,
        "op5_exact_dedup": op5_exact_dedup,
        "op6_token_files": op6_token_files,
        "op7_quality": op7_quality,
        "op8_sharding": op8_sharding,
        "op9_decontamination": op9_decontamination,
        "op10_language_model": op10_language_model,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op5_exact_dedup": r"""
            WITH n AS (SELECT doc_id, sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')) AS text_sha256 FROM documents)
            SELECT doc_id, min(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = min(doc_id) OVER w AS kept, text_sha256
            FROM n WINDOW w AS (PARTITION BY text_sha256)""",
    }
