"""Star platforms: one row per worker, with link time c per tile, compute time w per update, m buffers and side g."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilestar.functions.layout import side_overlap
from tilestar.runtime import table

SCHEMA = "platform_id int, worker_id int, c bigint, w bigint, m bigint, g bigint"
#: The two worked examples as (c, w, g) of each worker.
FAST_SLOW = ((1, 2, 2), (20, 40, 2))
THREE = ((2, 2, 6), (3, 3, 18), (5, 1, 10))


def literal(spark: SparkSession, workers: tuple[tuple[int, int, int], ...], platform_id: int = 0) -> DataFrame:
    return spark.createDataFrame([(platform_id, k + 1, c, w, g * g + 4 * g, g) for k, (c, w, g) in enumerate(workers)], SCHEMA)


def alike(spark: SparkSession, p: int, c: int, w: int, m: int) -> DataFrame:
    """p equal workers."""
    rows = spark.range(1, p + 1).select(F.lit(0).alias("platform_id"), F.col("id").cast("int").alias("worker_id"), *(F.lit(x).cast("bigint").alias(n) for n, x in (("c", c), ("w", w), ("m", m))))
    return rows.withColumn("g", side_overlap(F.col("m")))


def regions(spark: SparkSession, sf: str) -> DataFrame:
    """A platform per region; its suppliers are the workers."""
    joined = table(spark, sf, "supplier").join(table(spark, sf, "nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    rows = joined.select(
        F.col("n_regionkey").alias("platform_id"),
        F.col("s_suppkey").cast("int").alias("worker_id"),
        (1 + F.col("s_suppkey") % 5).cast("bigint").alias("c"),
        (1 + F.col("s_nationkey") % 7).cast("bigint").alias("w"),
        (21 + (F.col("s_suppkey") * 37) % 400).cast("bigint").alias("m"),
    )
    return rows.withColumn("g", side_overlap(F.col("m")))


REGIONS_SQL = """
SELECT n_regionkey AS platform_id, s_suppkey::INTEGER AS worker_id, (1 + s_suppkey % 5)::BIGINT AS c, (1 + s_nationkey % 7)::BIGINT AS w,
       (21 + (s_suppkey * 37) % 400)::BIGINT AS m, (floor(sqrt(25 + (s_suppkey * 37) % 400)) - 2)::BIGINT AS g
FROM supplier JOIN nation ON s_nationkey = n_nationkey
"""


def orders(spark: SparkSession, sf: str, many: int, workers: int) -> DataFrame:
    """`many` platforms of so many workers: a worker stands for the orders of one remainder of the customer's and of the order's key; its times and buffers come from their number and keys."""
    rows = table(spark, sf, "orders").filter("o_custkey is not null and o_orderkey is not null")
    keys = (F.col("o_custkey") % many).cast("int").alias("platform_id"), (1 + F.col("o_orderkey") % workers).cast("int").alias("worker_id")
    each = rows.groupBy(*keys).agg((1 + F.count("*") % 5).alias("c"), (1 + F.sum("o_custkey") % 7).alias("w"), (21 + F.sum("o_orderkey") % 400).alias("m"))
    return each.withColumn("g", side_overlap(F.col("m")))


def orders_sql(many: int, workers: int) -> str:
    return f"""SELECT *, (floor(sqrt(m + 4)) - 2)::BIGINT AS g FROM (SELECT (o_custkey % {many})::INTEGER AS platform_id, (1 + o_orderkey % {workers})::INTEGER AS worker_id,
(1 + count(*) % 5)::BIGINT AS c, (1 + sum(o_custkey) % 7)::BIGINT AS w, (21 + sum(o_orderkey) % 400)::BIGINT AS m FROM orders WHERE o_custkey IS NOT NULL AND o_orderkey IS NOT NULL GROUP BY 1, 2)"""
