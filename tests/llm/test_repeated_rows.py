"""Repeated rows and rows without an id in the near-dedup stage and after it."""

import collections

import pytest

import corpus_pipeline
from tilestar.llm import simhash

TEXT = {name: " ".join(f"{name}{k}" for k in range(50)) for name in "abcd"}
ROWS = [(1, TEXT["a"], "en")] * 3 + [(None, TEXT["b"], "en")] * 2 + [(None, TEXT["c"], "en"), (7, TEXT["c"], "en"), (8, TEXT["d"], "en"), (8, TEXT["d"], "de")]


@pytest.mark.parametrize("keep", [lambda spark, df: simhash.keep_one(df), lambda spark, df: corpus_pipeline.near_dedup(spark, df, "")])
def test_one_row_of_each_component_stays_and_keeps_its_text(spark, keep):
    kept = keep(spark, spark.createDataFrame(ROWS, "doc_id bigint, text string, lang string"))
    cut = corpus_pipeline.substring_dedup(spark, kept, "")
    got = collections.Counter((r["doc_id"], r["text"]) for r in cut.collect())
    assert got == collections.Counter([(1, TEXT["a"]), (None, TEXT["b"]), (7, TEXT["c"]), (8, TEXT["d"])])
