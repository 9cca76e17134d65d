"""Communication volume of the layouts, and lower bounds for any order of the standard product."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window
from pyspark.sql import functions as F


def up(a: Column, b: Column) -> Column:
    """a / b rounded up, whole numbers."""
    return F.floor((a + b - 1) / b).cast("bigint")


def chunk_volume(g: Column, t: Column) -> Column:
    """Tiles sent and returned for one g x g chunk: its C twice, and g A and g B tiles for each of t inner steps."""
    return 2 * g * g + 2 * g * t


def traffic_ratio(g: Column, t: Column) -> Column:
    """Tiles moved per tile update."""
    return 2.0 / t + 2.0 / g


def traffic_ratio_limit(m: Column) -> Column:
    return 2.0 / F.sqrt(m.cast("double"))


def traffic_ratio_elements(g: Column, t: Column, q: Column) -> Column:
    return traffic_ratio(g, t) / q


def problem_volume(r: Column, t: Column, s: Column, g: Column) -> Column:
    """Tiles through the port for one product: C in and out, A once a chunk column, B once a chunk row."""
    return 2 * r * s + r * t * up(s, g) + t * s * up(r, g)


def lower_bound_product(m: Column) -> Column:
    return F.sqrt(27.0 / (8.0 * m))


def lower_bound_pairwise(m: Column) -> Column:
    return F.sqrt(27.0 / (32.0 * m))


def lower_bound_prior(m: Column) -> Column:
    return F.sqrt(1.0 / (8.0 * m))


def update_cap_pairwise(a: Column, b: Column, c: Column) -> Column:
    """Updates that a A, b B and c C elements allow, by the weaker lemma."""
    root = lambda x: F.sqrt(x.cast("double"))
    return F.least((a + b) * root(c), (a + c) * root(b), (b + c) * root(a))


def update_cap_product(a: Column, b: Column, c: Column) -> Column:
    return F.sqrt(a.cast("double") * b * c)


def min_messages(u: Column, m: Column, product: bool = True) -> Column:
    """Whole messages that u updates need; 0 where the window argument says nothing."""
    k = (8.0 / 27.0) ** 0.5 if product else (32.0 / 27.0) ** 0.5
    return (m * F.floor(u / (k * m * F.sqrt(m.cast("double"))))).cast("bigint")


def startup_loss(c: Column, w: Column, g: Column, t: Column, p: Column) -> tuple[Column, Column]:
    """Share of time lost to the serial traffic of C, and its bound."""
    return 2.0 * c * p / (t * w), g / t.cast("double") + 2.0 * c / (t * w)


def bound_grid(shares: DataFrame, n: int) -> DataFrame:
    """Shares (a, b, c) in n-ths of the memory that maximise either cap, among those of `shares` (a, b) with the most for c that keeps their sum at 2 or less."""
    grid = shares.withColumn("c", F.least(F.lit(n), 2 * n - F.col("a") - F.col("b"))).filter("c >= 1")
    x = [F.col(v) / float(n) for v in "abc"]
    grid = grid.withColumns({"pairwise": update_cap_pairwise(*x), "product": update_cap_product(*x)})
    pick = lambda k: F.max_by(F.struct("a", "b", "c"), F.struct(F.round(k, 12), -F.col("a"), -F.col("b")))
    kinds = [grid.agg(F.max(F.round(k, 9)).alias("k"), pick(k).alias("at")).select(F.lit(k).alias("cap"), "k", "at.a", "at.b", "at.c") for k in ("pairwise", "product")]
    return kinds[0].union(kinds[1])


def tile_messages(spark: SparkSession, r: int, t: int, s: int, g: int) -> DataFrame:
    """(step, kind, held_a, held_b, held_c): the messages, tile by tile, of the schedule that keeps one A, g B and g x g C, and what is held before each.

    A chunk receives its C; for each inner step g tiles of B, then those of A one by one; then returns C. Chunks go down a column of chunks, then the next.
    """
    rows, cols = -(-r // g), -(-s // g)
    chunk = spark.range(rows * cols).select("id", F.least(F.lit(g), r - (F.col("id") % rows) * g).alias("a"), F.least(F.lit(g), s - F.floor(F.col("id") / rows) * g).alias("b"))
    a, b, p = F.col("a"), F.col("b"), F.col("p")
    chunk = chunk.withColumn("n", 2 * a * b + t * (a + b))
    first = F.coalesce(F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy("id").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a chunk
    each = chunk.withColumn("first", first).select("first", "a", "b", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n") - 1)).alias("p"))
    q = p - a * b
    k, o = F.floor(q / (a + b)), q % (a + b)
    moving = (q >= 0) & (q < t * (a + b))
    kind = F.when(q < 0, "C").when(~moving, "R").when(o < b, "B").otherwise("A")
    held = lambda x: F.when(moving, x).otherwise(0).cast("bigint")
    return each.select(
        (F.col("first") + p).alias("step"),
        kind.alias("kind"),
        held(F.least(F.lit(1), k * a + F.greatest(F.lit(0), o - b))).alias("held_a"),
        held(F.least(b, k * b + F.least(o, b))).alias("held_b"),
        (F.least(p, a * b) - F.greatest(F.lit(0), q - t * (a + b))).cast("bigint").alias("held_c"),
    )


def window_balance(messages: DataFrame, m: int) -> DataFrame:
    """For every m consecutive messages: tiles held at their start, tiles sent and returned, and whether held <= m and sent + returned = m."""
    w = Window.partitionBy(F.lit(0)).orderBy("step").rowsBetween(0, m - 1)  # a schedule is one sequence
    count = lambda kind, name: F.sum(F.when(F.col("kind") == kind, 1).otherwise(0)).over(w).alias(name)
    sums = [count("A", "sent_a"), count("B", "sent_b"), count("C", "sent_c"), count("R", "returned")]
    rows = messages.select("step", "held_a", "held_b", "held_c", *sums, F.count("*").over(w).alias("n")).filter(F.col("n") == m)
    fits = F.col("held_a") + F.col("held_b") + F.col("held_c") <= m
    return rows.drop("n").withColumns({"fits": fits, "balanced": F.col("sent_a") + F.col("sent_b") + F.col("sent_c") + F.col("returned") == m})


def balance_sql(r: int, t: int, s: int, g: int, m: int) -> str:
    """window_balance of tile_messages: DuckDB. Held tiles are counted from the messages themselves."""
    over = f"OVER (ORDER BY step ROWS BETWEEN CURRENT ROW AND {m - 1} FOLLOWING)"
    past = "OVER (PARTITION BY chunk ORDER BY p ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
    return f"""
WITH c AS (SELECT cj * {-(-r // g)} + ci AS chunk, least({g}, {r} - ci * {g}) AS a, least({g}, {s} - cj * {g}) AS b FROM range({-(-r // g)}) x(ci), range({-(-s // g)}) y(cj)),
e AS (SELECT chunk, a, b, 'C' AS kind, 0 AS k, n FROM c, range(0, 100) z(n) WHERE n < a * b UNION ALL SELECT chunk, a, b, 'B', k, n FROM c, range(1, {t + 1}) y(k), range(0, 100) z(n) WHERE n < b
  UNION ALL SELECT chunk, a, b, 'A', k, 100 + n FROM c, range(1, {t + 1}) y(k), range(0, 100) z(n) WHERE n < a UNION ALL SELECT chunk, a, b, 'R', {t + 1}, n FROM c, range(0, 100) z(n) WHERE n < a * b),
o AS (SELECT *, row_number() OVER (ORDER BY chunk, k, n) - 1 AS step, row_number() OVER (PARTITION BY chunk ORDER BY k, n) AS p FROM e),
h AS (SELECT step, kind, CASE WHEN kind = 'R' THEN 0 ELSE least(1, coalesce(count(*) FILTER (kind = 'A') {past}, 0)) END AS held_a,
  CASE WHEN kind = 'R' THEN 0 ELSE least(b, coalesce(count(*) FILTER (kind = 'B') {past}, 0)) END AS held_b,
  coalesce(count(*) FILTER (kind = 'C') {past}, 0) - coalesce(count(*) FILTER (kind = 'R') {past}, 0) AS held_c FROM o),
w AS (SELECT step, held_a, held_b, held_c, count(*) FILTER (kind = 'A') {over} AS sent_a, count(*) FILTER (kind = 'B') {over} AS sent_b,
  count(*) FILTER (kind = 'C') {over} AS sent_c, count(*) FILTER (kind = 'R') {over} AS returned, count(*) {over} AS n FROM h)
SELECT step::BIGINT AS step, held_a::BIGINT AS held_a, held_b::BIGINT AS held_b, held_c::BIGINT AS held_c, sent_a, sent_b, sent_c, returned,
       held_a + held_b + held_c <= {m} AS fits, sent_a + sent_b + sent_c + returned = {m} AS balanced FROM w WHERE n = {m}
"""
