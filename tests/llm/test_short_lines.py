"""Line dedup on short lines and on rows that share an id, by brute force."""

import numpy as np

from tilestar.llm import linededup


def within_one(a, b):
    if len(a) > len(b):
        a, b = b, a
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b, strict=True)) <= 1
    return len(b) == len(a) + 1 and any(b[:k] + b[k + 1 :] == a for k in range(len(b)))


def brute(rows):
    seen, out = [], []
    for i, text in rows:
        kept = []
        for line in text.split("\n"):
            key = line.strip(" \t\n\x0b\x0c\r")
            if not key or not any(within_one(key, s) for s in seen):
                kept.append(line)
            if key:
                seen.append(key)
        out.append((i, "\n".join(kept)))
    return out


def test_lines_of_every_length(spark):
    rng = np.random.default_rng(8)
    rows = [(k, "\n".join("".join(rng.choice(list("abé"), rng.integers(0, 20))) for _ in range(3))) for k in range(40)]
    got = {r["doc_id"]: r["text"] for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == dict(brute(rows))


def test_a_least_length_is_a_parameter(spark):
    df = spark.createDataFrame([(1, "ab"), (2, "ac"), (3, "ab"), (4, "long enough line"), (5, "long enough lime")], "doc_id bigint, text string")
    got = {r["doc_id"]: r["text"] for r in linededup.dedup_lines(df, min_chars=10).collect()}
    assert got == {1: "ab", 2: "ac", 3: "", 4: "long enough line", 5: ""}


def test_rows_of_one_id_are_documents_of_their_own(spark):
    df = spark.createDataFrame([(1, "alpha"), (1, "beta"), (0, "beta"), (None, "gamma"), (None, "delta"), (2, "gamma")], "doc_id bigint, text string")
    got = sorted((r["doc_id"] is None, r["doc_id"] or 0, r["text"]) for r in linededup.dedup_lines(df).collect())
    assert got == [(False, 0, "beta"), (False, 1, ""), (False, 1, "alpha"), (False, 2, ""), (True, 0, "delta"), (True, 0, "gamma")]
