"""Sparse tiles, expressions, user functions and tile files against NumPy and small hand-made cases."""

import numpy as np
import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from tilestar.functions import udfs
from tilestar.operators import lu, sparse, tiles
from tilestar.plans import expr
from tilestar.runtime import Scratch
from tilestar.sources import tilefile

CELLS = "row bigint, col bigint, val double"


def cells_of(spark, x):
    return spark.createDataFrame([(int(i), int(j), float(x[i, j])) for i, j in np.argwhere(x)] , CELLS)


def dense(df, shape):
    out = np.zeros(shape)
    for r in df.collect():
        out[r["row"], r["col"]] += r["val"]
    return out


@pytest.mark.parametrize(("r", "t", "s", "q", "g", "fill"), [(7, 9, 5, 2, 2, 0.3), (12, 3, 12, 4, 1, 0.9), (1, 20, 1, 3, 5, 0.5), (8, 8, 8, 8, 1, 0.05)])
def test_sparse_product(spark, r, t, s, q, g, fill):
    rng = np.random.default_rng(r * t)
    a, b = (np.where(rng.random(shape) < fill, rng.integers(-5, 6, shape), 0) for shape in ((r, t), (t, s)))
    out = sparse.resident_multiply(sparse.to_sparse(cells_of(spark, a), q), sparse.to_sparse(cells_of(spark, b), q), -(-r // q), -(-s // q), g, q)
    rows = out.collect()
    assert all(list(x["ptr"]) == sorted(x["ptr"]) and len(x["ptr"]) == q + 1 and x["ptr"][-1] == len(x["idx"]) == len(x["val"]) > 0 for x in rows)
    assert np.array_equal(dense(sparse.to_cells(out, q), (r, s)), a @ b)


def test_sparse_odd_cells(spark):
    empty = spark.createDataFrame([], CELLS)
    some = spark.createDataFrame([(0, 0, 1.0), (0, 0, 2.0), (None, 1, 3.0), (1, None, 3.0), (1, 1, None), (3, 1, 4.0)], CELLS)
    assert {tuple(x) for x in sparse.to_cells(sparse.to_sparse(some, 2), 2).collect()} == {(0, 0, 3.0), (3, 1, 4.0)}
    one = sparse.to_sparse(some, 2)
    for a, b in ((sparse.to_sparse(empty, 2), one), (one, sparse.to_sparse(empty, 2))):
        assert sparse.resident_multiply(a, b, 2, 2, 1, 2).count() == 0


def test_sparse_sends_what_has_a_partner(spark):
    a = sparse.to_sparse(spark.createDataFrame([(0, 0, 1.0), (0, 5, 1.0)], CELLS), 1)
    b = sparse.to_sparse(spark.createDataFrame([(0, 0, 1.0), (7, 0, 1.0)], CELLS), 1)
    assert {tuple(x) for x in sparse.volume(a, b, 4, 4, 2).collect()} == {("A", 2), ("B", 2)}


def test_expressions(spark):
    rng = np.random.default_rng(3)
    x, y = rng.integers(-4, 5, (6, 4)), rng.integers(-4, 5, (4, 6))
    leaf = lambda name, m: expr.Matrix(*m.shape, name, cells_of(spark, m).withColumn("val", F.col("val").cast("bigint")))
    a, b = leaf("X", x), leaf("Y", y)
    for tree, want in (
        ((a @ b).T.T @ a, x @ y @ x), ((a @ b + b.T @ a.T).row_sums(), (x @ y + (x @ y).T).sum(1, keepdims=True)), ((a @ b).T.col_sums(), (x @ y).T.sum(0, keepdims=True)),
        ((a @ b).trace(), np.array([[np.trace(x @ y)]])), ((a @ b).T.trace(), np.array([[np.trace(x @ y)]])), (b.T.row_sums(), y.T.sum(1, keepdims=True)),
    ):
        new = expr.rewrite(tree)
        assert np.array_equal(dense(expr.lower(tree), want.shape), want)
        assert np.array_equal(dense(expr.lower(new), want.shape), want)
        assert expr.multiplications(new) <= expr.multiplications(tree)
        assert expr.rewrite(new) == new
    with pytest.raises(ValueError):
        a @ a
    with pytest.raises(ValueError):
        a.trace()


def test_tile_functions(spark):
    udfs.register(spark)
    df = spark.createDataFrame([(1, [1.0, 2.0, 3.0, 4.0]), (1, None), (1, [1.0, 0.0, 0.0, 1.0]), (2, None)], "k int, tile array<double>")
    got = df.select("k", udfs.dot_tile("tile", "tile").alias("d"), udfs.gemm_tile("tile", "tile").alias("g")).collect()
    assert [x["d"] for x in got] == [30.0, None, 2.0, None]
    assert [x["g"] for x in got] == [[7.0, 10.0, 15.0, 22.0], None, [1.0, 0.0, 0.0, 1.0], None]
    assert {x["k"]: x["tile"] for x in df.groupBy("k").agg(udfs.tile_sum_group("tile").alias("tile")).collect()} == {1: [2.0, 2.0, 3.0, 5.0], 2: None}
    assert {x["k"]: x["tile"] for x in udfs.tile_sum(df, ["k"]).collect()} == {1: [2.0, 2.0, 3.0, 5.0]}
    sides = spark.sql("SELECT m, side_overlap(m) AS a, side_plain(m) AS b FROM VALUES (0L), (5L), (12L), (9007199254740993L) t(m)").collect()
    assert [(x["a"], x["b"]) for x in sides] == [(0, 0), (1, 1), (2, 2), (94906263, 94906264)]


def test_tile_files(spark):
    tilefile.register(spark)
    path = Scratch(spark, "tiles-test").base
    read = lambda q=3: spark.read.format("tiles").option("q", q).load(path)
    assert read().count() == 0
    x = np.arange(1, 50).reshape(7, 7)
    own = tiles.to_tiles(cells_of(spark, x), 3)
    own.write.format("tiles").option("q", 3).mode("append").save(path)
    assert np.array_equal(dense(tiles.to_cells(read(), 3), (7, 7)), x)
    own.limit(0).write.format("tiles").option("q", 3).mode("append").save(path)
    assert read().count() == 9
    own.filter("bi = 0").write.format("tiles").option("q", 3).mode("overwrite").save(path)
    assert read().count() == 3
    with pytest.raises(PySparkException):
        read(5).count()
    bad = spark.createDataFrame([(0, 0, None)], tilefile.SCHEMA)
    with pytest.raises(PySparkException):
        bad.write.format("tiles").option("q", 3).mode("append").save(path)
    assert read().count() == 3


def test_solve_and_determinant(spark):
    rng = np.random.default_rng(5)
    m = rng.integers(-3, 4, (7, 7)) + np.diag([30, -30, 30, 30, -30, -30, 30])
    x = np.arange(1, 8)
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(m @ x)], "row bigint, y double")
    got = {r["row"]: r["x"] for r in lu.solve(cells_of(spark, m), y, 7, 3, Scratch(spark, "solve")).collect()}
    assert sorted(got) == list(range(7)) and np.allclose([got[k] for k in range(7)], x)
    row = lu.log_det(cells_of(spark, m), 7, 3, Scratch(spark, "det")).first()
    sign, log = np.linalg.slogdet(m)
    assert row["sign"] == sign and row["log_det"] == pytest.approx(log)
