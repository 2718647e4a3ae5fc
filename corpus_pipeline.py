"""From raw documents to token ids: quality, exact copies, near copies, benchmark passages, piece encoding.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame, which is written as Parquet and read again as the next one's
``docs``. All but the last return the columns of ``documents``; the last returns ids and checks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from finegrain.llm import contamination, exact_dedup, near_dedup, pieces, quality
from finegrain.llm.entries import piece_model
from finegrain.sources.staging import staged
from finegrain.sources.tables import load


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    return quality.keep_good(docs, load(spark, sf_dir, "labels"))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the least id stays."""
    return exact_dedup.exact_dedup(docs).filter("kept").select(*docs.columns)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of near duplicates the one with the least id stays."""
    return near_dedup.without_near_duplicates(docs)


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return contamination.decontaminated(docs, load(spark, sf_dir, "benchmark", ["item_id", "text"]))


def piece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of every text, with the checks of its round trip."""
    return pieces.encoded_digests(docs, piece_model())


STAGES = [
    ("quality", quality_stage),
    ("exact_dedup", exact_stage),
    ("near_dedup", near_stage),
    ("decontamination", benchmark_stage),
    ("sentencepiece", piece_stage),
]

#: The stages fit a model, draw samples and solve best paths: tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table ``documents``."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = staged(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
