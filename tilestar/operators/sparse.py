"""Sparse tiles (compressed rows) and the resident-result product on them.

A sparse tile is a row (bi, bj, ptr, idx, val): ptr has q+1 entries, the cells of tile row x are idx/val[ptr[x] : ptr[x+1]], columns ascending. Only tiles with a cell
exist. Null coordinates or values are no cells; repeated coordinates are summed; cells that sum to zero are left out of results.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPARSE = "bi int, bj int, ptr array<int>, idx array<int>, val array<double>"


def _batch(keys: list[tuple[int, int]], cells: list[tuple[np.ndarray, np.ndarray]], q: int) -> pa.RecordBatch:
    """cells: (place, value) of each tile, places ascending."""
    n = len(keys)
    ends = np.concatenate(([0], np.cumsum([len(p) for p, _ in cells]))).astype(np.int32)
    place = np.concatenate([p for p, _ in cells])
    ptr = np.concatenate([np.searchsorted(p, np.arange(q + 1) * q) for p, _ in cells]).astype(np.int32)
    lists = lambda at, x: pa.ListArray.from_arrays(pa.array(at), pa.array(x))
    columns = [
        pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys], pa.int32()), lists(np.arange(n + 1, dtype=np.int32) * (q + 1), ptr),
        lists(ends, (place % q).astype(np.int32)), lists(ends, np.concatenate([v for _, v in cells]).astype(np.float64)),
    ]
    return pa.RecordBatch.from_arrays(columns, names=["bi", "bj", "ptr", "idx", "val"])


def to_sparse(df: DataFrame, q: int, row: str = "row", col: str = "col", val: str = "val") -> DataFrame:
    """Coordinates to sparse tiles. Cells are summed before they are gathered, so a group has q*q of them at most."""
    r, c = F.col(row), F.col(col)
    cells = df.select(r.alias("row"), c.alias("col"), F.col(val).cast("double").alias("x")).dropna().groupBy("row", "col").agg(F.sum("x").alias("x"))
    place = (F.col("row") % q * q + F.col("col") % q).cast("int").alias("place")
    cells = cells.select(F.floor(F.col("row") / q).cast("int").alias("bi"), F.floor(F.col("col") / q).cast("int").alias("bj"), F.struct(place, "x").alias("cell"))
    parts = cells.groupBy("bi", "bj").agg(F.sort_array(F.collect_list("cell")).alias("cells")).select("bi", "bj", "cells.place", "cells.x")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                keys = list(zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True))
                yield _batch(keys, [(np.asarray(p.values), np.asarray(x.values)) for p, x in zip(b.column(2), b.column(3), strict=True)], q)

    return parts.mapInArrow(pack, SPARSE)


def to_cells(tiles: DataFrame, q: int) -> DataFrame:
    """Sparse tiles to coordinates (row, col, val)."""
    spans = tiles.select("bi", "bj", "idx", "val", F.explode(F.transform(F.sequence(F.lit(0), F.lit(q - 1)), lambda x: F.struct(x.alias("x"), F.get("ptr", x).alias("at"), F.get("ptr", x + 1).alias("upto")))).alias("s"))
    length = F.col("s.upto") - F.col("s.at")
    one = F.arrays_zip(F.slice("idx", F.col("s.at") + 1, length).alias("idx"), F.slice("val", F.col("s.at") + 1, length).alias("val"))
    each = spans.filter(length > 0).select("bi", "bj", "s.x", F.explode(one).alias("cell"))
    return each.select((F.col("bi").cast("bigint") * q + F.col("x")).alias("row"), (F.col("bj").cast("bigint") * q + F.col("cell.idx")).alias("col"), "cell.val")


def replicated(a: DataFrame, b: DataFrame, r: int, s: int, g: int) -> DataFrame:
    """The tiles that the product sends: A to all chunk columns, B to all chunk rows, without those that have no partner."""
    nr, nc = -(-r // g), -(-s // g)
    steps = lambda x, k: x.select(F.col(k).alias("__k")).distinct()
    a = a.join(steps(b, "bi"), F.col("bj") == F.col("__k"), "left_semi")
    b = b.join(steps(a, "bj"), F.col("bi") == F.col("__k"), "left_semi")
    every = lambda n, name: F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias(name)
    part = lambda x: F.floor(F.col(x) / g).cast("int")
    rest = ["bi", "bj", "ptr", "idx", "val"]
    rows = a.select(part("bi").alias("ci"), every(nc, "cj"), F.col("bj").alias("k"), F.lit(1).alias("kind"), *rest)
    return rows.unionByName(b.select(every(nr, "ci"), part("bj").alias("cj"), F.col("bi").alias("k"), F.lit(0).alias("kind"), *rest))


def volume(a: DataFrame, b: DataFrame, r: int, s: int, g: int) -> DataFrame:
    """(kind, tiles): messages of A and B that `resident_multiply` sends, counted before the exchange."""
    return replicated(a, b, r, s, g).groupBy(F.when(F.col("kind") == 1, "A").otherwise("B").alias("kind")).agg(F.count("*").alias("tiles"))


def resident_multiply(a: DataFrame, b: DataFrame, r: int, s: int, g: int, q: int) -> DataFrame:
    """A*B for sparse tiles. r, s: tile rows and columns of the result; g: side of the resident square in tiles.

    A task holds the touched tiles of one square of the result (dense, g*g at most), one row of sparse B tiles and one A tile.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk, k_now = None, None
        square: dict[tuple[int, int], np.ndarray] = {}
        row: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]] = []

        def flush() -> Iterator[pa.RecordBatch]:
            for key in sorted(square):
                place = np.flatnonzero(square[key])
                if len(place):
                    yield _batch([key], [(place, square[key][place])], q)

        for batch in batches:
            ci, cj, k, kind, bi, bj = (batch.column(n).to_numpy() for n in range(6))
            for n in range(batch.num_rows):
                if (ci[n], cj[n]) != chunk:
                    yield from flush()
                    chunk, k_now, square, row = (ci[n], cj[n]), None, {}, []
                if k[n] != k_now:
                    k_now, row = k[n], []
                ptr, idx, val = (np.asarray(batch.column(c)[n].values) for c in (6, 7, 8))
                if kind[n] == 0:
                    row.append((int(bj[n]), ptr, idx, val))
                    continue
                own = np.repeat(np.arange(q), np.diff(ptr))
                for j, ptr_b, idx_b, val_b in row:
                    first = ptr_b[idx]
                    count = ptr_b[idx + 1] - first
                    total = int(count.sum())
                    if not total:
                        continue
                    at = np.repeat(first - np.cumsum(count) + count, count) + np.arange(total)
                    tile = square.setdefault((int(bi[n]), j), np.zeros(q * q))
                    np.add.at(tile, np.repeat(own * q, count) + idx_b[at], np.repeat(val, count) * val_b[at])
        yield from flush()

    tasks = int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return replicated(a, b, r, s, g).repartition(tasks, "ci", "cj").sortWithinPartitions("ci", "cj", "k", "kind").mapInArrow(run, SPARSE)
