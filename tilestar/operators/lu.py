"""Blocked right-looking LU without pivoting, on tiles, and the costs and plans of its parallel form.

The input must allow elimination without pivoting (for instance by a dominant diagonal); a pivot of zero raises an error.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilestar.functions.bounds import up
from tilestar.operators.tiles import TILE, _tile_array, block, resident_multiply, retile, to_cells, to_tiles
from tilestar.plans import select
from tilestar.runtime import Scratch


def eliminate(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """L (unit lower) and U of one dense block."""
    u, n = x.astype(float).copy(), len(x)
    low = np.eye(n)
    for k in range(n):
        if u[k, k] == 0:
            raise ZeroDivisionError(f"zero pivot at {k}")
        low[k + 1 :, k] = u[k + 1 :, k] / u[k, k]
        u[k + 1 :] -= np.outer(low[k + 1 :, k], u[k])
    return low, np.triu(u)


def forward(low: np.ndarray, x: np.ndarray) -> np.ndarray:
    """y with low @ y = x for a lower triangle; x: (..., n, m)."""
    y = x.astype(float).copy()
    for k in range(len(low)):
        y[..., k, :] = (y[..., k, :] - (low[k, :k] @ y[..., :k, :])) / low[k, k]
    return y


def factor(tiles: DataFrame, n: int, q: int, scratch: Scratch, g: int = 1) -> tuple[DataFrame, DataFrame]:
    """(L, U) of an n x n tile matrix, g tile rows and columns a step (the second level of blocks). The control loop runs on the driver; tiles stay on the executors, but for the
    pivot block of g x g tiles, which one worker's memory holds.

    Every step writes the remaining core, so that no lineage builds up. The padded edge of the last tile must have ones on its diagonal.
    """
    if g > 1:
        blocks, side = -(-n // g), g * q
        beyond = tiles.sparkSession.range(n * q, blocks * side).select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(1.0).alias("val"))
        whole = to_tiles(to_cells(tiles, q).select("row", "col", "val").unionByName(beyond), side)
        return tuple(block(retile(x, side, q), (0, n), (0, n)) for x in factor(whole, blocks, side, scratch))
    spark = tiles.sparkSession
    core, lows, ups = scratch.save(tiles, "core0"), [], []
    for k in range(n):
        first = core.filter((F.col("bi") == k) & (F.col("bj") == k)).collect()  # one tile
        low, upper = eliminate(np.array(first[0]["tile"]).reshape(q, q) if first else np.zeros((q, q)))
        ends = spark.createDataFrame([(k, k, low.ravel().tolist(), upper.ravel().tolist())], "bi int, bj int, low array<double>, up array<double>")

        def solve(by: np.ndarray, right: bool):
            """Rows x of the vertical panel become x U^-1, columns y of the horizontal panel L^-1 y, by substitution."""

            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for b in batches:
                    if b.num_rows:
                        x = np.asarray(b.column(2).flatten()).reshape(-1, q, q)
                        y = forward(by.T, x.swapaxes(1, 2)).swapaxes(1, 2) if right else forward(by, x)
                        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), _tile_array(np.ascontiguousarray(y).reshape(len(x), -1))], names=["bi", "bj", "tile"])

            return run

        column = scratch.save(core.filter((F.col("bj") == k) & (F.col("bi") > k)).mapInArrow(solve(upper, True), TILE), f"column{k}")
        row = scratch.save(core.filter((F.col("bi") == k) & (F.col("bj") > k)).mapInArrow(solve(low, False), TILE), f"row{k}")
        lows += [ends.select("bi", "bj", F.col("low").alias("tile")), column]
        ups += [ends.select("bi", "bj", F.col("up").alias("tile")), row]
        if k == n - 1:
            break
        rest = core.filter((F.col("bi") > k) & (F.col("bj") > k))
        both = rest.select("bi", "bj", "tile").unionByName(_outer(column, row, q, n))
        core = scratch.save(_sum_tiles(both, q), f"core{k + 1}")
        scratch.drop(f"core{k}")
    return _union(lows), _union(ups)


def residual(m: DataFrame, low: DataFrame, upper: DataFrame, n: int, q: int) -> DataFrame:
    """(largest, relative): of m - L U, the greatest absolute value, and its Frobenius norm over that of m. m (row, col, val), factors of n x n tiles."""
    back = to_cells(resident_multiply(low, upper, n, n, max(1, n // 2), q), q).select("row", "col", (-F.col("val")).alias("val"))
    cells = m.select("row", "col", F.col("val").cast("double").alias("val"))
    both = cells.unionByName(back.join(F.broadcast(cells.agg(F.max("row").alias("r"), F.max("col").alias("c"))), (F.col("row") <= F.col("r")) & (F.col("col") <= F.col("c"))).select("row", "col", "val"))
    left = both.groupBy("row", "col").agg(F.sum("val").alias("val"))
    size = cells.agg(F.sum(F.col("val") * F.col("val")).alias("all"))
    return left.agg(F.max(F.abs("val")).alias("largest"), F.sum(F.col("val") * F.col("val")).alias("rest")).crossJoin(size).select("largest", F.sqrt(F.col("rest") / F.col("all")).alias("relative"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _outer(column: DataFrame, row: DataFrame, q: int, n: int) -> DataFrame:
    """Minus the products of a tile column and a tile row, through the resident-result product."""
    minus = column.withColumn("tile", F.transform("tile", lambda x: -x))
    return resident_multiply(minus, row, n, n, max(1, min(-(-n // 4), 32)), q)


def _sum_tiles(tiles: DataFrame, q: int) -> DataFrame:
    parts = tiles.groupBy("bi", "bj").agg(F.collect_list("tile").alias("tiles"))  # two tiles a group at most
    return parts.select("bi", "bj", F.aggregate(F.slice("tiles", 2, 1), F.col("tiles")[0], lambda a, b: F.zip_with(a, b, lambda x, y: x + y)).alias("tile"))


def _substitute(tri: DataFrame, y: DataFrame, n: int, q: int, scratch: Scratch, upper: bool) -> DataFrame:
    """(row, y) of the solution of a triangular system of n x n tiles: a tile column a step. One tile and q numbers are on the driver at a time."""
    name, place = ("up" if upper else "low"), F.floor(F.col("row") / q)
    spark, y = tri.sparkSession, scratch.save(y.groupBy("row").agg(F.sum(F.col("y").cast("double")).alias("y")), f"{name}-y")
    for step, k in enumerate(reversed(range(n)) if upper else range(n)):
        pivot = tri.filter((F.col("bi") == k) & (F.col("bj") == k)).first()
        known = np.zeros(q)
        for row in y.filter(place == k).collect():  # q rows at most
            known[row["row"] - k * q] = row["y"]
        x = np.linalg.solve(np.array(pivot["tile"]).reshape(q, q), known)
        scratch.save(spark.createDataFrame([(k * q + i, float(v)) for i, v in enumerate(x)], "row bigint, y double"), f"{name}-x/k={k}")

        def minus(batches: Iterator[pa.RecordBatch], x: np.ndarray = x) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    part = -(np.asarray(b.column(1).flatten()).reshape(-1, q, q) @ x)
                    rows = b.column(0).to_numpy()[:, None].astype(np.int64) * q + np.arange(q)
                    yield pa.RecordBatch.from_arrays([pa.array(rows.ravel()), pa.array(part.ravel())], names=["row", "y"])

        others = tri.filter((F.col("bj") == k) & (F.col("bi") != k)).select("bi", "tile").mapInArrow(minus, "row bigint, y double")
        y = scratch.save(y.filter(place != k).unionByName(others).groupBy("row").agg(F.sum("y").alias("y")), f"{name}-y{step}")
    return spark.read.parquet(f"{scratch.base}/{name}-x").select("row", "y")


def _factors_of(m: DataFrame, n: int, q: int, scratch: Scratch) -> tuple[DataFrame, DataFrame, int]:
    """Factors of an n x n matrix (row, col, val), and their side in tiles. Rows beyond the edge and rows without a cell get a pivot of one."""
    blocks = -(-n // q)
    pad = m.sparkSession.range(blocks * q).join(m.select("row").distinct(), F.col("id") == F.col("row"), "left_anti").select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(1.0).alias("val"))
    low, upper = factor(to_tiles(m.select("row", "col", F.col("val").cast("double").alias("val")).unionByName(pad), q), blocks, q, scratch)
    return scratch.save(low, "low"), scratch.save(upper, "upper"), blocks


def solve(m: DataFrame, y: DataFrame, n: int, q: int, scratch: Scratch) -> DataFrame:
    """(row, x) with m x = y, for m (row, col, val) that can be factored and y (row, y); rows without a y have zero."""
    low, upper, blocks = _factors_of(m, n, q, scratch)
    half = _substitute(low, y, blocks, q, scratch, upper=False)
    return _substitute(upper, half, blocks, q, scratch, upper=True).filter(F.col("row") < n).withColumnRenamed("y", "x")


def log_det(m: DataFrame, n: int, q: int, scratch: Scratch) -> DataFrame:
    """(log_det, sign): logarithm of the determinant's absolute value, and its sign."""
    _, upper, _ = _factors_of(m, n, q, scratch)
    each = upper.filter("bi = bj").select(F.posexplode("tile").alias("at", "u")).filter(F.col("at") % (q + 1) == 0)
    return each.agg(F.sum(F.log(F.abs("u"))).alias("log_det"), F.when(F.sum(F.when(F.col("u") < 0, 1).otherwise(0)) % 2 == 1, -1).otherwise(1).alias("sign"))


def costs(df: DataFrame) -> DataFrame:
    """df (r, g) with r a multiple of g: per step k the tile messages and updates of pivot, panels and core; then totals are sums."""
    n = F.floor(F.col("r") / F.col("g")).cast("bigint")
    rows = df.select("r", "g", n.alias("n"), F.explode(F.sequence(F.lit(1).cast("bigint"), n)).alias("k"))
    g, rest, left = F.col("g"), F.col("r") - F.col("k") * F.col("g"), F.col("n") - F.col("k")
    return rows.select(
        "r", "g", "k",
        (2 * g * g).alias("pivot_messages"), (g * g * g).alias("pivot_updates"),
        (4 * g * rest).alias("panel_messages"), (g * g * rest).alias("panel_updates"),
        (left * (g * g + 3 * g * rest)).alias("core_messages"), (left * rest * g * g).alias("core_updates"),
    )


def totals(df: DataFrame) -> DataFrame:
    """(r, g, messages, updates, core_updates) as sums over the steps, with the closed forms beside them."""
    each = costs(df).groupBy("r", "g").agg(
        F.sum(F.col("pivot_messages") + F.col("panel_messages") + F.col("core_messages")).alias("messages"),
        F.sum(F.col("pivot_updates") + F.col("panel_updates") + F.col("core_updates")).alias("updates"),
        F.sum("core_updates").alias("core_updates"),
    )
    r, g = F.col("r"), F.col("g")
    div = lambda a, b: F.floor(a / b).cast("bigint")
    return each.withColumns({"messages_closed": div(r * r * r, g) + r * r, "updates_closed": div(r * r * r + 2 * g * g * r, F.lit(3)), "core_closed": div(2 * r * r * r - 3 * g * r * r + g * g * r, F.lit(6))})


def chunk_shape(df: DataFrame) -> DataFrame:
    """df (g, gi), gi below g: square chunk against whole columns for a worker smaller than the block side; quality is updates per tile moved."""
    g, gi = F.col("g"), F.col("gi")
    width = F.greatest(F.floor(gi * gi / g).cast("bigint"), F.lit(1).cast("bigint"))
    square, columns = gi / 3.0, gi * gi / (g + 2.0 * gi * gi / g)
    return df.withColumns({"width": width, "square": F.round(square, 9), "columns": F.round(columns, 9), "shape": F.when(2 * gi <= g, "square").otherwise("columns")})


def virtual_workers(df: DataFrame) -> DataFrame:
    """df (worker_id, g, gi), gi at least g: a row per virtual worker that fits."""
    n = F.floor(F.col("gi") * F.col("gi") / (F.col("g") * F.col("g"))).cast("bigint")
    return df.select("worker_id", "g", "gi", F.explode(F.sequence(F.lit(1).cast("bigint"), n)).alias("part"))


def plan(platform: DataFrame, r: int, rule: str = "global", steps: int = 60) -> DataFrame:
    """For each platform the block side of least estimated time: (platform_id, g, time).

    Every side up to the largest worker's is tried, divisors of r or not. Pivots and panels go to the worker that does them fastest. The core's whole column blocks are dealt by the
    selection of the product, on rows of the core: a worker of the side's memory or more moves 3 g tiles for g * g updates (the virtual workers that fit share its link and its
    speed, so they are one), a smaller one has the better of its two chunk shapes. The rate of `steps` messages carries the core's updates.
    """
    own = platform.filter("g > 0").select("platform_id", "worker_id", "c", "w", "g")
    top = own.groupBy("platform_id").agg(F.least(F.max("g"), F.lit(r).cast("bigint")).alias("top"))
    rows = top.select("platform_id", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("top"))).alias("side")).join(own, "platform_id")
    g, gi, c = F.col("side"), F.col("g"), F.col("c")
    width = F.greatest(F.floor(gi * gi / g).cast("bigint"), F.lit(1).cast("bigint"))
    send = F.when(gi >= g, 3 * g * c).when(2 * gi <= g, 3 * gi * c).otherwise((g + 2 * width) * c)
    gain = F.when(gi >= g, g * g).when(2 * gi <= g, gi * gi).otherwise(g * width)
    numbered = rows.withColumns({"send": send, "gain": gain, "square": F.lit(0).cast("bigint"), "platform_id": (F.col("platform_id") * 10_000 + g).cast("int")})
    folded = select.fold(select.as_rows(numbered), steps, rule)
    rate = folded.select(F.floor(F.col("platform_id") / 10_000).cast("int").alias("platform_id"), (F.col("platform_id") % 10_000).cast("bigint").alias("side"), F.element_at("works", -1).alias("work"), F.element_at("ends", -1).alias("end"))
    each = rate.select("*", F.explode(F.sequence(F.lit(1).cast("bigint"), F.ceil(F.lit(r) / F.col("side")))).alias("k"))
    size, rest = F.least("side", r - (F.col("k") - 1) * F.col("side")), F.greatest(F.lit(0).cast("bigint"), r - F.col("k") * F.col("side"))
    sums = each.groupBy("platform_id", "side", "work", "end").agg(
        F.sum(2 * size * size + 4 * size * rest).alias("messages"), F.sum(size * size * size + size * size * rest).alias("updates"), F.sum(rest * rest * size).alias("core")
    )
    panel = sums.join(own, "platform_id").groupBy("platform_id", "side", "work", "end", "core").agg(F.min(F.col("messages") * c + F.col("updates") * F.col("w")).alias("panel"))
    est = panel.select("platform_id", F.col("side").alias("g"), (F.col("panel") + F.col("core") * F.col("end").cast("double") / F.col("work")).alias("time"))
    return est.groupBy("platform_id").agg(F.min_by("g", F.struct(F.round("time", 6), F.col("g"))).alias("g"), F.round(F.min("time"), 3).alias("time"))


def plan_sql(platform_sql: str, r: int, steps: int = 60) -> str:
    """`plan` by the global rule: DuckDB."""
    shaped = f"""SELECT (platform_id * 10000 + side)::INTEGER AS platform_id, worker_id, c, w, g,
 CASE WHEN g >= side THEN 3 * side * c WHEN 2 * g <= side THEN 3 * g * c ELSE (side + 2 * greatest(g * g // side, 1)) * c END AS send,
 CASE WHEN g >= side THEN side * side WHEN 2 * g <= side THEN g * g ELSE side * greatest(g * g // side, 1) END AS gain
FROM ({platform_sql}) o, range(1, {r + 1}) t(side) WHERE g > 0 AND side <= (SELECT max(g) FROM ({platform_sql}) z WHERE z.platform_id = o.platform_id)"""
    return f"""
WITH tr AS ({select.selection_sql(shaped, steps, message=("send", "gain"))}),
e AS (SELECT platform_id // 10000 AS platform_id, platform_id % 10000 AS side, work, finish FROM tr WHERE step = {steps}),
k AS (SELECT e.*, least(side, {r} - (k - 1) * side) AS p, greatest(0, {r} - k * side) AS rest FROM e, range(1, {r + 1}) t(k) WHERE (k - 1) * side < {r}),
s AS (SELECT platform_id, side, work, finish, sum(2 * p * p + 4 * p * rest) AS messages, sum(p * p * p + p * p * rest) AS updates, sum(rest * rest * p) AS core FROM k GROUP BY ALL),
b AS (SELECT s.platform_id, side, work, finish, core, min(messages * c + updates * w) AS panel FROM s JOIN ({platform_sql}) o ON o.platform_id = s.platform_id WHERE o.g > 0 GROUP BY ALL),
t AS (SELECT platform_id, side AS g, panel + core * finish::DOUBLE / work AS time FROM b)
SELECT platform_id::INTEGER AS platform_id, arg_min(g, {{'t': round(time, 6), 'g': g}})::BIGINT AS g, round(min(time), 3)::DOUBLE AS time FROM t GROUP BY 1
"""


def enrolled(g: Column, c: Column, w: Column) -> Column:
    """Workers on the core beside the one that does pivots and panels."""
    return up(g * w, 3 * c)
