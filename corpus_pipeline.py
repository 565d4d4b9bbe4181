"""Corpus pipeline: quality, toxicity, near duplicates, benchmark passages, tokens.

Each stage takes (spark, docs, sf_dir) and works on all rows that its predecessor kept; its result
is written as Parquet and read again as the next one's docs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowloom.llm import decontam, neardup, pieces, quality, toxicity
from rowloom.llm.queries import tokenizer_path
from rowloom.llm.shared import table, written


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the quality classifier rejects (score under 0.3)."""
    model = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.keep(docs, model)


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the toxicity model rejects (score 0.5 or more)."""
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.keep(docs, model)


def neardup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document, that with the smallest id, of each group of near duplicates (similarity 0.8 or more)."""
    copies = neardup.near_duplicates(docs, threshold=80).where("not kept").select(F.col("doc_id").cast("long").alias("copy_id")).distinct()
    return docs.join(copies.hint("merge"), F.col("doc_id") == F.col("copy_id"), "left_anti")


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents with a benchmark window in them."""
    return decontam.keep(docs, table(spark, sf_dir, "benchmark"))


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids, original byte spans and digests of every document left."""
    return pieces.encode_documents(docs, tokenizer_path())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", quality_stage),
    ("toxicity", toxicity_stage),
    ("near_duplicates", neardup_stage),
    ("decontamination", decontamination_stage),
    ("encoding", encoding_stage),
]

#: The stages' models and components have no SQL form; tests compare them with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
