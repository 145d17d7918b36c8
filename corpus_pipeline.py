"""A corpus pipeline of five stages, each written and read again by the next.

Every stage works on all rows that the one before kept. All but the last return
the columns of ``documents``; the last returns piece ids. No stage has an SQL
counterpart: the first is a fitted model and the fourth a hash-driven draw.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cutfold.functions.storage import drop_saved, saved, scope
from cutfold.llm import exact_dedup, language_id, mixing, pieces, simhash_dedup


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a recognisable language go (NULL or letter-free texts)."""
    return language_id.reject_unknown(docs)


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts stays."""
    return exact_dedup.exact_dedup(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by similarity 0.8 of five-word shingles stays."""
    return simhash_dedup.near_dedup(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents appear as often as the mix of sources takes them."""
    return mixing.mix_documents(docs)


def piece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Per document its piece ids."""
    return pieces.encode_documents(docs, keep=("doc_id", "lang", "source"))


STAGES = [
    ("language_id", language_stage),
    ("exact_dedup", exact_stage),
    ("simhash_near_dedup", near_stage),
    ("mix_sources", mixing_stage),
    ("sentence_pieces", piece_stage),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order over ``documents``."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES:
        with scope() as tables:
            out = tables.keep(saved(stage(spark, docs, sf_dir), f"pipeline-{name}"))
        if before is not None:
            drop_saved(before)
        docs = before = out
    return docs
