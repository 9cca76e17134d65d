"""Corpus pipeline: quality rules, line dedup, near-dedup, substring dedup, packing.

Every stage takes all rows that the stage before kept, and its decisions take effect. All but the last return the columns of documents.
Each stage's result is written as Parquet into shared scratch storage and read again as the next one's documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tilestar.llm import linededup, nearcopies, packing, quality, substring
from tilestar.runtime import Scratch, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the current policy accepts."""
    return quality.keep(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents; of equal or nearly equal lines the earliest stays. n_chars is that of the text as it was."""
    return linededup.dedup_lines(docs).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near copies (0.8 or more of their five-word shingles; SimHash trie, then an exact join), that of the smallest doc_id."""
    return nearcopies.keep_one(docs).select(*docs.columns)


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the words of passages that stand elsewhere too."""
    return substring.cut(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 1024 tokens with their sequences."""
    return packing.pack(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("simhash_near_dedup", near_dedup),
    ("substring_dedup", substring_dedup),
    ("best_fit_packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch, docs = Scratch(spark, "pipeline"), table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = scratch.save(docs, name)
    return docs


#: Byte-level BPE and components of near copies have no SQL form; tests/llm/test_pipeline_brute.py holds run() against the five stages in plain Python.
ORACLE_SQL = None
