"""Reference blocks of the substring operator: crowds, large blocks, and rows that share an id."""

import collections
import hashlib

import numpy as np
import pytest

from tests.llm.test_operators import brute_cut
from tilestar.llm import substring


def corpus():
    rng = np.random.default_rng(21)
    vocabulary = [f"v{k}" for k in range(6)]
    passage, seed = [str(x) for x in rng.choice(vocabulary, 300)], [f"s{k}" for k in range(30)]
    docs = []
    for k in range(60):
        w = [f"a{k}x{j}" for j in range(rng.integers(0, 9))]
        at = int(rng.integers(0, 250))
        w += passage[at : at + int(rng.integers(30, 50))] + [f"b{k}"] + seed + [f"c{int(rng.integers(4))}"] * int(rng.integers(0, 12))  # all share the seed, most differ around it
        docs.append((k, " ".join(w)))
    return docs


@pytest.mark.parametrize("crowd,block", [(32, 4096), (2, 4096), (1, 3), (32, 3)])
def test_crowds_and_large_blocks(spark, monkeypatch, crowd, block):
    monkeypatch.setattr(substring, "CROWD", crowd)
    monkeypatch.setattr(substring, "BLOCK", block)
    docs = corpus()
    df = spark.createDataFrame(docs, "doc_id bigint, text string").repartition(5)
    got = collections.Counter((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring.op9_substring_dedup(df).collect())
    assert got == brute_cut(docs) and any(r[2] for r in got)


def test_rows_of_one_id_and_without_one(spark):
    passage = " ".join(f"p{k}" for k in range(50))
    rows = [(1, f"first {passage}"), (1, f"{passage} second"), (1, "third text of one id")] + [(None, f"n{k} " + " ".join(f"n{k}x{j}" for j in range(40))) for k in range(300)] + [(None, f"n7 {passage} end")]
    got = collections.Counter((r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring.op9_substring_dedup(spark.createDataFrame(rows, "doc_id bigint, text string")).collect())
    sha = lambda t: hashlib.sha256(t.encode()).hexdigest()
    assert got == collections.Counter([x[1:] for x in brute_cut(list(enumerate(t for _, t in rows))).elements()])
    assert got[(51, 50, sha("first"))] == got[(51, 50, sha("second"))] == got[(52, 50, sha("n7 end"))] == 1
