"""Queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from tilestar.llm import bpe, html, licenses, linededup, neighbours, packing, quality, simhash, substring, toxicity
from tilestar.runtime import table


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality": lambda s, d: quality.op1_quality(table(s, d, "documents")),
        "op4_line_dedup": lambda s, d: linededup.op4_line_dedup(table(s, d, "documents")),
        "op6_simhash": lambda s, d: simhash.op6_simhash(table(s, d, "documents")),
        "op9_substring_dedup": lambda s, d: substring.op9_substring_dedup(table(s, d, "documents")),
        "op5_bpe": lambda s, d: bpe.op5_bpe(table(s, d, "documents")),
        "op8_packing": lambda s, d: packing.op8_packing(table(s, d, "documents")),
        "op2_toxicity": lambda s, d: toxicity.op2_toxicity(table(s, d, "documents"), table(s, d, "labels")),
        "op10_html": lambda s, d: html.op10_html(table(s, d, "pages")),
        "op7_licenses": lambda s, d: licenses.op7_licenses(table(s, d, "documents")),
        "op3_neighbours": lambda s, d: neighbours.op3_neighbours(table(s, d, "embeddings")),
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_quality": quality.SQL, "op4_line_dedup": linededup.SQL, "op7_licenses": licenses.SQL, "op9_substring_dedup": substring.SQL}
