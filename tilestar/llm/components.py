"""Connected components of an edge table by alternating star contraction, in DataFrames.

Every round replaces edges by edges to smaller nodes: first each node's larger neighbours are hung on its smallest
neighbour, then each node and its smaller neighbours on the smallest. Rounds grow with the logarithm of the
number of nodes; each round is written to shared scratch storage, so no lineage builds up and a lost executor costs one round.
Minima are combined before the shuffle, and joins on a hub are left to adaptive skew handling.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilestar.runtime import Scratch


def components(edges: DataFrame, scratch: Scratch, name: str = "stars") -> DataFrame:
    """edges (a, b) of one ordered type, self-loops and repeats allowed -> (node, root), for each node with an edge: its smallest reachable node.

    An empty edge table gives an empty result. Nulls take no part.
    """
    now = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a < b").distinct()
    now, before, k = scratch.save(now, f"{name}0"), None, 0
    while True:
        # larger neighbours of u go to the smallest of u and its neighbours
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).union(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").filter("v > u").select(F.col("m").alias("a"), F.col("v").alias("b")).filter("a < b").distinct()
        # u and its smaller neighbours go to the smallest of them
        low = large.groupBy("b").agg(F.min("a").alias("m"))
        small = large.join(low, "b").select(F.col("m").alias("x"), F.explode(F.array("a", "b")).alias("y")).filter("x < y")
        k += 1
        after = scratch.save(small.select(F.col("x").alias("a"), F.col("y").alias("b")).distinct(), f"{name}{k}")
        scratch.drop(f"{name}{k - 1}")
        mark = after.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first()
        now = after
        if mark == before:
            return now.select(F.col("b").alias("node"), F.col("a").alias("root")).union(now.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct())
        before = mark
