"""Tiled matrices, and the resident-result product on them with NumPy, a bounded number of tiles in memory at a time.

A tile is a row (bi, bj, tile): q*q doubles, row-major; the ragged edge is zero-padded; missing tiles are zero.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TILE = "bi int, bj int, tile array<double>"


def _tile_array(tiles: np.ndarray) -> pa.Array:
    n = len(tiles)
    flat = np.ascontiguousarray(tiles, np.float64).ravel()
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * (len(flat) // n if n else 0)), pa.array(flat))


def to_tiles(df: DataFrame, q: int, row: str = "row", col: str = "col", val: str = "val") -> DataFrame:
    """Coordinates to tiles; repeated coordinates are summed."""
    r, c = F.col(row), F.col(col)
    place = (r % q * q + c % q).cast("int")
    cells = df.select(F.floor(r / q).cast("int").alias("bi"), F.floor(c / q).cast("int").alias("bj"), place.alias("place"), F.col(val).cast("double").alias("x"))
    parts = cells.groupBy("bi", "bj").agg(F.collect_list("place").alias("at"), F.collect_list("x").alias("x"))  # at most q*q distinct cells a group, if summed before

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            tiles = np.zeros((b.num_rows, q * q))
            for k, (at, x) in enumerate(zip(b.column(2), b.column(3), strict=True)):
                np.add.at(tiles[k], np.asarray(at.values), np.asarray(x.values))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), _tile_array(tiles)], names=["bi", "bj", "tile"])

    return parts.mapInArrow(fill, TILE)


def to_cells(tiles: DataFrame, q: int) -> DataFrame:
    """Tiles to the coordinates that are not zero: (row, col, val)."""
    each = tiles.select("bi", "bj", F.posexplode("tile").alias("n", "val")).filter("val <> 0")
    return each.select((F.col("bi").cast("bigint") * q + F.floor(F.col("n") / q)).alias("row"), (F.col("bj").cast("bigint") * q + F.col("n") % q).alias("col"), "val")


def resident_multiply(a: DataFrame, b: DataFrame, r: int, s: int, g: int, q: int, c: DataFrame | None = None) -> DataFrame:
    """C + A*B. r, s: tile rows and columns of the result; g: side of the resident square in tiles.

    Every A tile goes to all chunk columns and every B tile to all chunk rows; a task reads its chunks' tiles in the order of the inner index and holds one square of C, one
    row of B and one A tile at a time: 1 + g + g*g tiles.
    """
    nr, nc = -(-r // g), -(-s // g)
    every = lambda n, name: F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias(name)
    part = lambda x: F.floor(F.col(x) / g).cast("int")
    rows = a.select(part("bi").alias("ci"), every(nc, "cj"), F.col("bj").alias("k"), F.lit(1).alias("kind"), "bi", "bj", "tile")
    rows = rows.unionByName(b.select(every(nr, "ci"), part("bj").alias("cj"), F.col("bi").alias("k"), F.lit(0).alias("kind"), "bi", "bj", "tile"))
    if c is not None:
        rows = rows.unionByName(c.select(part("bi").alias("ci"), part("bj").alias("cj"), F.lit(-1).alias("k"), F.lit(2).alias("kind"), "bi", "bj", "tile"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # the square as strips of q rows, and which of its tiles there are; the row of B as one wide block, so an A tile is one multiplication
        chunk, k_now, square, there, row, wide, at = None, None, {}, set(), {}, None, None

        def strip(i: int) -> np.ndarray:
            if i not in square:
                square[i] = np.zeros((q, g * q))
            return square[i]

        def flush() -> Iterator[pa.RecordBatch]:
            keys = sorted(there)
            if keys:
                own = _tile_array(np.stack([square[i][:, j * q : j * q + q].ravel() for i, j in keys]))
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in keys], pa.int32()), pa.array([int(chunk[1]) * g + j for _, j in keys], pa.int32()), own], names=["bi", "bj", "tile"])

        for batch in batches:
            ci, cj, k, kind, bi, bj = (batch.column(n).to_numpy() for n in range(6))
            for n, tile in enumerate(batch.column(6)):
                if (ci[n], cj[n]) != chunk:
                    yield from flush()
                    chunk, k_now, square, there = (ci[n], cj[n]), None, {}, set()
                if k[n] != k_now:
                    k_now, row, wide = k[n], {}, None
                x = np.asarray(tile.values).reshape(q, q)
                i, j = int(bi[n]), int(bj[n]) - int(cj[n]) * g
                if kind[n] == 2:
                    strip(i)[:, j * q : j * q + q] += x
                    there.add((i, j))
                elif kind[n] == 0:
                    row[j] = row.get(j, 0) + x
                elif row:
                    if wide is None:
                        cols = sorted(row)
                        wide = np.concatenate([row[c] for c in cols], axis=1)
                        at = slice(cols[0] * q, cols[-1] * q + q) if cols[-1] - cols[0] + 1 == len(cols) else np.concatenate([np.arange(c * q, c * q + q) for c in cols])
                    strip(i)[:, at] += x @ wide
                    there.update((i, c) for c in row)
        yield from flush()

    tasks = int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(tasks, "ci", "cj").sortWithinPartitions("ci", "cj", "k", "kind").mapInArrow(run, TILE)


def transpose(df: DataFrame) -> DataFrame:
    return df.select(F.col("col").alias("row"), F.col("row").alias("col"), "val")


def add(x: DataFrame, y: DataFrame, scale: int = 1) -> DataFrame:
    """x + scale * y, coordinates (row, col, val)."""
    return x.unionByName(y.withColumn("val", F.col("val") * scale)).groupBy("row", "col").agg(F.sum("val").alias("val"))


def hadamard(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.join(y.withColumnRenamed("val", "other"), ["row", "col"]).select("row", "col", (F.col("val") * F.col("other")).alias("val"))


def product(x: DataFrame, y: DataFrame) -> DataFrame:
    """(row, col, val) of x*y, by the inner index."""
    left, right = x.select("row", F.col("col").alias("k"), "val"), y.select(F.col("row").alias("k"), "col", F.col("val").alias("other"))
    return left.join(right, "k").groupBy("row", "col").agg(F.sum(F.col("val") * F.col("other")).alias("val"))


def power(x: DataFrame, n: int) -> DataFrame:
    """x to the n-th, by repeated squaring; n at least 1."""
    out = None
    while n:
        if n & 1:
            out = x if out is None else product(out, x)
        n >>= 1
        if n:
            x = product(x, x)
    return out


def matvec(x: DataFrame, v: DataFrame) -> DataFrame:
    """(row, y) of x times v (k, x)."""
    return x.join(v.withColumnRenamed("k", "col"), "col").groupBy("row").agg(F.sum(F.col("val") * F.col("x")).alias("y"))


def chain_order(dims: list[int]) -> tuple[int, str]:
    """Fewest multiplications for a chain of matrices dims[0] x dims[1], dims[1] x dims[2], ..., and the bracketing."""
    n = len(dims) - 1
    cost = {(i, i): (0, f"M{i + 1}") for i in range(n)}
    for width in range(1, n):
        for i in range(n - width):
            j = i + width
            cost[i, j] = min((cost[i, k][0] + cost[k + 1, j][0] + dims[i] * dims[k + 1] * dims[j + 1], f"({cost[i, k][1]}{cost[k + 1, j][1]})") for k in range(i, j))
    return cost[0, n - 1]


def retile(tiles: DataFrame, q: int, side: int) -> DataFrame:
    """The same matrix with tiles of another side; the edge is padded by zeros."""
    return to_tiles(to_cells(tiles, q).select("row", "col", "val"), side)


def block(tiles: DataFrame, rows: tuple[int, int], cols: tuple[int, int]) -> DataFrame:
    """Tiles of rows [r0, r1) and columns [c0, c1), numbered from 0; the bounds reach the scan as filters."""
    inside = (F.col("bi") >= rows[0]) & (F.col("bi") < rows[1]) & (F.col("bj") >= cols[0]) & (F.col("bj") < cols[1])
    return tiles.filter(inside).withColumns({"bi": F.col("bi") - rows[0], "bj": F.col("bj") - cols[0]})


def norms(cells: DataFrame) -> DataFrame:
    """(largest, one, inf, square) of a matrix (row, col, val): greatest absolute value, greatest column and row sum of absolute values, sum of squares."""
    size = F.abs("val")
    sums = lambda key: cells.groupBy(key).agg(F.sum(size).alias("s")).agg(F.max("s"))
    one, inf = sums("col").toDF("one"), sums("row").toDF("inf")
    return cells.agg(F.max(size).alias("largest"), F.sum(F.col("val") * F.col("val")).alias("square")).crossJoin(one).crossJoin(inf).select("largest", "one", "inf", "square")  # one row each
