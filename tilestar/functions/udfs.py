"""Functions for users of tiles in SQL and DataFrames: tile products and sums through Arrow, a table function of schedules, SQL functions of the layouts.

Null tiles give null (products) or are left out (sums); tiles of unequal length raise.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType

from tilestar.plans.schedulers import play

STEPS = "step int, worker_id int, kind string, start bigint, finish bigint, tiles bigint"


@pandas_udf(DoubleType())
def dot_tile(a: pd.Series, b: pd.Series) -> pd.Series:
    """Sum of the products of two tiles' cells."""
    return pd.Series([None if x is None or y is None else float(np.dot(x, y)) for x, y in zip(a, b, strict=True)], dtype="Float64")


@pandas_udf(ArrayType(DoubleType()))
def gemm_tile(a: pd.Series, b: pd.Series) -> pd.Series:
    """Matrix product of two square tiles, row-major."""

    def one(x, y):
        if x is None or y is None:
            return None
        q = round(len(x) ** 0.5)
        return (x.reshape(q, q) @ y.reshape(q, q)).ravel()

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)])


@pandas_udf(ArrayType(DoubleType()))
def tile_sum_group(tiles: pd.Series) -> list:
    """Sum of a group's tiles as a grouped aggregate; holds the group, so for bounded groups. tile_sum is the form without that bound."""
    own = tiles.dropna()
    return np.sum(np.stack(own.to_list()), axis=0) if len(own) else None


def tile_sum(df: DataFrame, keys: list[str], tile: str = "tile") -> DataFrame:
    """(keys, tile): sums of tiles by cell, with partial sums before the exchange, so a hot key costs a row per task and cell."""
    cells = df.select(*keys, F.posexplode(tile).alias("__n", "__x")).groupBy(*keys, "__n").agg(F.sum("__x").alias("__x"))
    sums = cells.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("__n", "__x"))).alias("cells"))  # a tile's cells: bounded by the tile
    return sums.select(*keys, F.col("cells.__x").alias(tile))


def _steps_udtf():
    @udtf(returnType=STEPS)
    class ScheduleSteps:
        """The messages of one scenario with p equal workers."""

        def eval(self, policy: str, r: int, t: int, s: int, p: int, c: int, w: int, m: int) -> Iterator[tuple]:
            for row in play(policy, r, t, s, [(c, w, m)] * p).rows:
                yield row[0], row[1], row[2], row[6], row[7], row[10]

    return ScheduleSteps


def register(spark: SparkSession) -> None:
    """Makes the functions known to SQL: dot_tile, gemm_tile, schedule_steps, side_overlap, side_plain, problem_volume."""
    spark.udf.register("dot_tile", dot_tile)
    spark.udf.register("gemm_tile", gemm_tile)
    spark.udtf.register("schedule_steps", _steps_udtf())
    root = "CAST(FLOOR(SQRT(m + {a})) AS BIGINT) - CASE WHEN POWER(FLOOR(SQRT(m + {a})), 2) > m + {a} THEN 1 ELSE 0 END - {b}"
    for name, a, b in (("side_overlap", 4, 2), ("side_plain", 1, 1)):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(m BIGINT) RETURNS BIGINT RETURN GREATEST({root.format(a=a, b=b)}, 0)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION problem_volume(r BIGINT, t BIGINT, s BIGINT, g BIGINT) RETURNS BIGINT"
        " RETURN 2 * r * s + r * t * ((s + g - 1) DIV g) + t * s * ((r + g - 1) DIV g)"
    )


def dot_column(a: str, b: str) -> Column:
    """dot_tile without Python: the two arrays zipped and folded."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda acc, x: acc + x)
