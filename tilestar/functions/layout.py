"""Memory layouts: the side of the resident square for m tile buffers, as exact integer column expressions.

A side below 1 means that the layout does not fit; callers treat it as an error or skip the worker.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def whole_root(x: Column) -> Column:
    """Largest s with s*s <= x, exact beyond the precision of doubles; 0 for x below 1."""
    s = F.floor(F.sqrt(F.greatest(x, F.lit(0)).cast("double"))).cast("bigint")
    return F.when(s * s > x, s - 1).when((s + 1) * (s + 1) <= x, s + 1).otherwise(s)


def side_single(m: Column) -> Column:
    """One A tile, g B tiles, g*g C tiles: largest g with 1 + g + g*g <= m."""
    return F.greatest(F.floor((whole_root(4 * m - 3) - 1) / 2).cast("bigint"), F.lit(0).cast("bigint"))


def side_overlap(m: Column) -> Column:
    """Double buffers: 2g A, 2g B, g*g C: largest g with g*g + 4g <= m."""
    return F.greatest(whole_root(m + 4) - 2, F.lit(0).cast("bigint"))


def side_plain(m: Column) -> Column:
    """No spare buffers: g A, g B, g*g C: largest g with g*g + 2g <= m."""
    return F.greatest(whole_root(m + 1) - 1, F.lit(0).cast("bigint"))


def side_third(m: Column) -> Column:
    """Three equal squares."""
    return whole_root(F.floor(m / 3).cast("bigint"))


def side_fifth(m: Column) -> Column:
    """Five equal squares."""
    return whole_root(F.floor(m / 5).cast("bigint"))


#: The LU chunk uses the double-buffered side.
side_lu = side_overlap
SIDES = {"single": side_single, "overlap": side_overlap, "plain": side_plain, "third": side_third, "fifth": side_fifth}


def buffers(size: Column, q: Column) -> Column:
    """Tile buffers of q*q doubles in `size` bytes."""
    return F.floor(size / (8 * q * q)).cast("bigint")


def sides(df: DataFrame, m: str = "m") -> DataFrame:
    """df with one column for the side of each layout."""
    return df.withColumns({f"g_{name}": f(F.col(m)) for name, f in SIDES.items()})


def side_rect(df: DataFrame, m: str = "m", r: str = "r", s: str = "s") -> DataFrame:
    """df with the rectangle a x b, a <= r, b <= s, a*b + 2(a+b) <= m, of least (a+b)/(ab); ties to the smaller a. sqrt(m) candidates a row."""
    a = F.explode(F.sequence(F.lit(1).cast("bigint"), F.least(F.col(r), F.greatest(F.floor((F.col(m) - 2) / 3).cast("bigint"), F.lit(1).cast("bigint"))))).alias("rect_a")
    cut = df.select("*", a).withColumn("rect_b", F.least(F.col(s), F.floor((F.col(m) - 2 * F.col("rect_a")) / (F.col("rect_a") + 2)).cast("bigint"))).filter("rect_b >= 1")
    keys = [F.col(c) for c in df.columns]
    best = F.min_by(F.struct("rect_a", "rect_b"), F.struct((F.col("rect_a") + F.col("rect_b")).cast("double") / (F.col("rect_a") * F.col("rect_b")), F.col("rect_a")))
    return cut.groupBy(*keys).agg(best.alias("best")).select(*df.columns, "best.rect_a", "best.rect_b")


def buffer_map(spark, g: int, t: int) -> DataFrame:
    """Which tile each of 1 + g + g*g buffers holds at each of the g*g*t updates of one chunk: (step, slot, matrix, bi, bj).

    Slot 0 has the A tile, slots 1..g the B row, the others the C square; a step is one A tile against one B tile.
    """
    step = spark.range(g * g * t).withColumnRenamed("id", "step")
    at = step.select("step", F.floor(F.col("step") / (g * g)).cast("bigint").alias("k"), (F.floor(F.col("step") / g) % g).cast("bigint").alias("i"))
    slot = F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(g + g * g).cast("bigint"))).alias("slot")
    rows = at.select("step", "k", "i", slot)
    n = F.col("slot")
    c = n - (g + 1)
    return rows.select(
        "step",
        "slot",
        F.when(n == 0, "A").when(n <= g, "B").otherwise("C").alias("matrix"),
        F.when(n == 0, F.col("i")).when(n <= g, F.col("k")).otherwise(F.floor(c / g).cast("bigint")).alias("bi"),
        F.when(n == 0, F.col("k")).when(n <= g, n - 1).otherwise(c % g).alias("bj"),
    )


def buffer_contents(a: DataFrame, b: DataFrame, g: int, t: int) -> DataFrame:
    """buffer_map with what each buffer holds after its step: the tile of A (i, k, v) or of B (k, j, u), and what C has summed up so far."""
    rows = buffer_map(a.sparkSession, g, t)
    met = a.join(b, "k").select("i", "j", (F.col("k") * g * g + F.col("i") * g + F.col("j")).alias("at"), (F.col("v") * F.col("u")).alias("x"))
    tiles = a.select(F.lit("A").alias("matrix"), F.col("i").alias("bi"), F.col("k").alias("bj"), F.lit(0).cast("bigint").alias("at"), F.col("v").alias("x"))
    tiles = tiles.unionByName(b.select(F.lit("B").alias("matrix"), F.col("k").alias("bi"), F.col("j").alias("bj"), F.lit(0).cast("bigint").alias("at"), F.col("u").alias("x")))
    tiles = tiles.unionByName(met.select(F.lit("C").alias("matrix"), F.col("i").alias("bi"), F.col("j").alias("bj"), "at", "x"))
    held = rows.join(tiles, ["matrix", "bi", "bj"], "left").groupBy(*rows.columns).agg(F.sum(F.when(F.col("at") <= F.col("step"), F.col("x"))).alias("held"))
    return held.withColumn("held", F.coalesce("held", F.lit(0).cast("bigint")))
