"""Recall of the neighbour graph on clustered vectors with small leaves, so that trees, splits, descent and search all matter."""

import numpy as np

from tilestar.llm import neighbours


def recall(spark, x, every):
    df = spark.createDataFrame([(k, v) for k, v in enumerate(x.tolist())], "vec_id bigint, embedding array<double>")
    got = neighbours.nearest(df, f"vec_id % {every} = 0").select("query_id", "rank", "vec_id", "score").collect()
    mine = {}
    for r in got:
        mine.setdefault(r["query_id"], set()).add(r["vec_id"])
    hits = total = 0
    for q in range(0, len(x), every):
        d = ((x - x[q]) ** 2).sum(axis=1)
        d[q] = np.inf
        hits += len(mine[q] & set(np.argsort(d, kind="stable")[:10].tolist()))
        total += 10
    return hits / total


def test_recall_on_a_clustered_table(spark, monkeypatch):
    for name, value in (("LEAF", 64), ("SAMPLE", 256)):
        monkeypatch.setattr(neighbours, name, value)
    rng = np.random.default_rng(5)
    centers = rng.normal(size=(30, 16))
    own = np.concatenate([np.zeros(3500, int), rng.integers(0, 30, 6500)])  # one cluster has more than a third of all rows
    x = centers[own] + rng.normal(scale=0.1, size=(10_000, 16))
    assert recall(spark, x, 100) >= 0.9


def test_each_vector_length_is_searched(spark):
    rows = [(k, [float(k), 1.0]) for k in range(6)] + [(100 + k, [float(k), 1.0, 2.0]) for k in range(3)] + [(200, [1.0])]
    got = neighbours.op3_neighbours(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")).orderBy("query_id", "rank").collect()
    assert [(r["query_id"], r["vec_id"]) for r in got] == [(0, 1), (0, 2), (0, 3), (0, 4), (0, 5), (100, 101), (100, 102)]
