"""The corpus pipeline: quality filter, line dedup, near dedup, packing; each stage on all that the one before it kept."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dagframe.llm import lines, packing, quality, simhash
from dagframe.llm.common import read_table, with_checkpoints


def quality_classifier(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, learnt from the labels of ``docs``, accepts."""
    return quality.keep_good(docs, read_table(spark, sf_dir, "labels"))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents without the lines that many of them share; the last holder keeps them. ``n_chars`` follows the text."""
    changed = {"text": F.col("kept"), "n_chars": F.length("kept").cast("long")}
    applied = lines.LineIndex.of(docs).apply(docs)
    return applied.select(*[changed.get(c, F.col("row").getField(c)).alias(c) for c in docs.columns])


def simhash_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies: fingerprints of five-word shingles that differ in at most 5 of 64 bits (0.92 alike)."""
    return simhash.keep_one(docs, shingle=5, distance=5)


def best_fit_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of at most 2048 tokens."""
    return packing.pack(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_classifier", quality_classifier),
    ("line_dedup", line_dedup),
    ("simhash_dedup", simhash_dedup),
    ("best_fit_packing", best_fit_packing),
]

#: The classifier, fingerprints and tokenizer have no SQL form; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; lineage is cut between them."""
    with_checkpoints(spark)
    docs = read_table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = docs.checkpoint()
    return docs
