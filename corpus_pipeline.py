"""The corpus pipeline: language ID, near-duplicate join, substring dedup, secret scan, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hetjoin.llm import jaccard_join, language_id, paragraph_dedup, secret_scan, slack_packing
from hetjoin.llm.shared import discard, written


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents of undetermined language: those without a letter. Short texts score low by chance and stay.

    Learns from the labelled documents that are not held out. Where no document has a label,
    nothing can be judged but the lack of letters.
    """
    prototypes = language_id.fit_prototypes(docs.where(~language_id.held_out(docs)))
    if not prototypes:
        return docs.where(F.coalesce(F.col("text"), F.lit("")).rlike(r"\p{L}"))
    found = language_id.labelled(docs, prototypes, keep=tuple(docs.columns)).where(F.col("lang_pred") != language_id.UNDETERMINED)
    return found.select(*[F.col(f"_{i}").alias(c) for i, c in enumerate(docs.columns)])


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one row of each group linked by similarity, that of the smallest id."""
    return jaccard_join.one_of_each(docs)


def cut_repeated_paragraphs(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts all but the first of similar paragraphs; documents stay."""
    return paragraph_dedup.cleaned(docs)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks values that only few owners have; documents stay."""
    return secret_scan.redact(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return slack_packing.pack(docs)


STAGES = [
    ("language_id", identify_language),
    ("jaccard_join", drop_near_duplicates),
    ("paragraph_dedup", cut_repeated_paragraphs),
    ("secret_scan", mask_secrets),
    ("best_fit_packing", pack_sequences),
]
# Stages learn, hash and tokenize in ways that SQL cannot express; tests hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``; each but the last is written and read again."""
    docs = spark.read.parquet(f"{sf_dir.rstrip('/')}/documents.parquet")
    for name, stage in STAGES[:-1]:
        before, docs = docs, written(stage(spark, docs, sf_dir), f"stage-{name}")
        discard(before)
    return STAGES[-1][1](spark, docs, sf_dir)
