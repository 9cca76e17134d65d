"""Matrices made from the given tables, in coordinate form. Sums of whole numbers, so products are exact."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilestar.runtime import table


def left(spark: SparkSession, sf: str, r: int, t: int) -> DataFrame:
    """A (i, k, v): quantities by (orderkey + suppkey) mod r and partkey mod t."""
    rows = table(spark, sf, "lineitem").select(((F.col("l_orderkey") + F.col("l_suppkey")) % r).alias("i"), (F.col("l_partkey") % t).alias("k"), F.col("l_quantity").cast("bigint").alias("x"))
    return rows.groupBy("i", "k").agg(F.sum("x").alias("v"))


def right(spark: SparkSession, sf: str, t: int, s: int) -> DataFrame:
    """B (k, j, u): quantities by partkey mod t and orderkey mod s."""
    rows = table(spark, sf, "lineitem").select((F.col("l_partkey") % t).alias("k"), (F.col("l_orderkey") % s).alias("j"), F.col("l_quantity").cast("bigint").alias("x"))
    return rows.groupBy("k", "j").agg(F.sum("x").alias("u"))


def start(spark: SparkSession, sf: str, r: int, s: int) -> DataFrame:
    """C0 (i, j, c): lines by (orderkey + suppkey) mod r and orderkey mod s, of orders that exist."""
    known = table(spark, sf, "orders").select("o_orderkey").distinct()
    rows = table(spark, sf, "lineitem").join(known, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    return rows.groupBy(((F.col("l_orderkey") + F.col("l_suppkey")) % r).alias("i"), (F.col("l_orderkey") % s).alias("j")).agg(F.count("*").alias("c"))


def embeddings(spark: SparkSession, sf: str) -> DataFrame:
    """(row, col, val): embeddings in thousandths."""
    rows = table(spark, sf, "embeddings").select(F.col("vec_id").alias("row"), F.posexplode("embedding").alias("col", "x"))
    return rows.select("row", F.col("col").cast("bigint").alias("col"), F.floor(F.col("x").cast("double") * 1000 + 0.5).cast("bigint").alias("val"))


def embedding_rows(spark: SparkSession, sf: str) -> DataFrame:
    """(id, val): as `embeddings`, a row as an array."""
    return table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: F.floor(x.cast("double") * 1000 + 0.5).cast("bigint")).alias("val"))


def trade(spark: SparkSession, sf: str) -> DataFrame:
    """(i, j, v): quantities from supplier nation to customer nation, with the row sum added to the diagonal."""
    line, supp, orders, cust = (table(spark, sf, x) for x in ("lineitem", "supplier", "orders", "customer"))
    rows = line.join(supp, F.col("l_suppkey") == F.col("s_suppkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(cust, F.col("o_custkey") == F.col("c_custkey"))
    cells = rows.groupBy(F.col("s_nationkey").alias("i"), F.col("c_nationkey").alias("j")).agg(F.sum(F.col("l_quantity").cast("bigint")).alias("v"))
    total = cells.groupBy("i").agg(F.sum("v").alias("v")).select("i", F.col("i").alias("j"), "v")
    return cells.unionByName(total).groupBy("i", "j").agg(F.sum("v").alias("v"))


def terms(df: DataFrame, id_col: str, text: str = "text") -> DataFrame:
    """(id, term, n): counts of lower-cased runs of ASCII letters."""
    word = F.explode(F.expr(f"regexp_extract_all(lower(`{text}`), '[a-z]+', 0)")).alias("term")
    return df.select(F.col(id_col).alias("id"), word).groupBy("id", "term").agg(F.count("*").alias("n"))


def a_sql(r: int, t: int) -> str:
    return f"SELECT (l_orderkey + l_suppkey) % {r} AS i, l_partkey % {t} AS k, sum(l_quantity::BIGINT)::BIGINT AS v FROM lineitem GROUP BY 1, 2"


def b_sql(t: int, s: int) -> str:
    return f"SELECT l_partkey % {t} AS k, l_orderkey % {s} AS j, sum(l_quantity::BIGINT)::BIGINT AS u FROM lineitem GROUP BY 1, 2"


EMBED_SQL = "SELECT vec_id AS row, (n - 1)::BIGINT AS col, floor(embedding[n]::DOUBLE * 1000 + 0.5)::BIGINT AS val FROM embeddings, range(1, 65) t(n)"
TRADE_SQL = """
WITH cells AS (
  SELECT s_nationkey AS i, c_nationkey AS j, sum(l_quantity::BIGINT)::BIGINT AS v
  FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2)
SELECT i, j, sum(v)::BIGINT AS v FROM (SELECT * FROM cells UNION ALL SELECT i, i, sum(v) FROM cells GROUP BY i) GROUP BY i, j
"""
