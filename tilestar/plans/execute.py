"""Runs a product as a selection planned it: each message of the trace brings its panel to the columns that its worker owns, in the order of the trace.

A worker's messages are counted: t of them make a chunk of g x g, ceil(r / g) chunks one block of g whole columns. Blocks get their columns in the order in which
the trace completes them, until s columns are owned; messages of blocks that come too late are not sent.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilestar.operators import multiply


def blocks(trace: DataFrame, platform: DataFrame, r: int, t: int, s: int) -> DataFrame:
    """(platform_id, worker_id, g, block, done, j0, j1): completed column blocks of each worker, and the columns that each owns."""
    per = (t * F.ceil(F.lit(r) / F.col("g"))).cast("bigint")
    own = Window.partitionBy("platform_id", "worker_id").orderBy("step")
    rows = trace.join(platform.select("platform_id", "worker_id", "g"), ["platform_id", "worker_id"]).withColumn("nth", F.row_number().over(own))
    ends = rows.filter(F.col("nth") % per == 0).select("platform_id", "worker_id", "g", (F.floor(F.col("nth") / per) - 1).alias("block"), F.col("step").alias("done"))
    order = Window.partitionBy("platform_id").orderBy("done")
    placed = ends.withColumn("j1", F.sum("g").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("j0", F.col("j1") - F.col("g"))
    return placed.filter(F.col("j0") < s).withColumn("j1", F.least("j1", F.lit(s).cast("bigint")))


def messages(trace: DataFrame, platform: DataFrame, r: int, t: int, s: int) -> DataFrame:
    """(platform_id, step, worker_id, k, i0, i1, j0, j1, a, b, c): every message that is sent, in the order of the trace: the panel of inner step k for the chunk
    of rows [i0, i1) and columns [j0, j1), its tiles of A and B, and of C where it opens the chunk."""
    g = F.col("g")
    per = (t * F.ceil(F.lit(r) / g)).cast("bigint")
    own = Window.partitionBy("platform_id", "worker_id").orderBy("step")
    rows = trace.withColumn("nth", F.row_number().over(own) - 1)
    rows = rows.join(blocks(trace, platform, r, t, s), ["platform_id", "worker_id"]).filter(F.col("block") == F.floor(F.col("nth") / per))
    ci, k = F.floor((F.col("nth") % per) / t), (F.col("nth") % t).cast("bigint")
    rows = rows.withColumns({"k": k, "i0": ci * g}).withColumn("i1", F.least(F.col("i0") + g, F.lit(r).cast("bigint")))
    a, b = F.col("i1") - F.col("i0"), F.col("j1") - F.col("j0")
    return rows.select("platform_id", "step", "worker_id", "k", "i0", "i1", "j0", "j1", a.alias("a"), b.alias("b"), F.when(F.col("k") == 0, a * b).otherwise(0).alias("c"))


def execute(a: DataFrame, b: DataFrame, sent: DataFrame, c: DataFrame | None = None) -> DataFrame:
    """C + A*B by the messages of one platform: a worker's chunks, and all panels sent to them, meet in the task of that worker.

    sent: as `messages` gives it; its rows are as many as the messages of the simulated port, far fewer than tiles, and travel as joins on the inner index.
    """
    chunk = [F.col("worker_id").alias("ci"), F.xxhash64("i0", "j0").alias("cj")]
    where = sent.select(*chunk, "k", "step", "i0", "i1", "j0", "j1")
    left = a.join(where, "k").filter((F.col("i") >= F.col("i0")) & (F.col("i") < F.col("i1"))).select("ci", "cj", "k", "i", "v")
    right = b.join(where, "k").filter((F.col("j") >= F.col("j0")) & (F.col("j") < F.col("j1"))).select("ci", "cj", "k", "j", "u")
    old = None
    if c is not None:
        first = where.filter("k = 0")
        inside = (F.col("i") >= F.col("i0")) & (F.col("i") < F.col("i1")) & (F.col("j") >= F.col("j0")) & (F.col("j") < F.col("j1"))
        old = c.join(first, inside).select("ci", "cj", "i", "j", "c")
    return multiply.owned(left, right, old)


def messages_sql(trace_sql: str, platform_sql: str, r: int, t: int, s: int) -> str:
    """Per worker, what `messages` sends for one platform: DuckDB."""
    return f"""
WITH tr AS ({trace_sql}),
x AS (SELECT tr.worker_id, step, g, row_number() OVER (PARTITION BY tr.worker_id ORDER BY step) - 1 AS nth, {t} * (({r} + g - 1) // g) AS per
      FROM tr JOIN ({platform_sql}) p ON p.worker_id = tr.worker_id),
o AS (SELECT worker_id, g, (nth + 1) // per - 1 AS block, sum(g) OVER (ORDER BY step) AS hi FROM x WHERE (nth + 1) % per = 0),
b AS (SELECT worker_id, block, least(hi, {s}) - (hi - g) AS width FROM o WHERE hi - g < {s}),
m AS (SELECT x.worker_id, step, nth % {t} AS k, least(g, {r} - ((nth % per) // {t}) * g) AS height, width FROM x JOIN b ON x.worker_id = b.worker_id AND block = nth // per)
SELECT worker_id, count(*)::BIGINT AS messages, sum(height)::BIGINT AS a, sum(width)::BIGINT AS b, sum(CASE WHEN k = 0 THEN height * width ELSE 0 END)::BIGINT AS c,
       min(step)::INTEGER AS first, max(step)::INTEGER AS last FROM m GROUP BY worker_id
"""
