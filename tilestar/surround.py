"""More queries: sparse tiles, matrix expressions, user functions, formats, samples, and cross-checks of the planners. Registered with those of `workloads`."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilestar.functions import bounds, layout, udfs
from tilestar.operators import lu, sparse, tiles
from tilestar.plans import expr, schedulers, select
from tilestar.runtime import Scratch, table
from tilestar.sources import matrices, platforms, tilefile
from tilestar.streaming import panels
from tilestar.workloads import ONE_WORKER, ORACLES, SHAPES, drawn_sql, product_sql, query

_T2 = "SELECT 0 AS platform_id, worker_id, c::BIGINT AS c, w::BIGINT AS w, g::BIGINT AS g FROM (VALUES (1, 2, 2, 6), (2, 3, 3, 18), (3, 5, 1, 10)) t(worker_id, c, w, g)"

# ---- sparse tiles ----------------------------------------------------------------------------------------------------------------------

_Q = 20


def _sparse(spark: SparkSession, sf: str, r: int, t: int, s: int) -> tuple[DataFrame, DataFrame, int, int]:
    scratch = Scratch(spark, "sparse")
    a = scratch.save(sparse.to_sparse(matrices.left(spark, sf, r, t).toDF("row", "col", "val"), _Q), "a")
    b = scratch.save(sparse.to_sparse(matrices.right(spark, sf, t, s).toDF("row", "col", "val"), _Q), "b")
    return a, b, -(-r // _Q), -(-s // _Q)


@query("sparse_tiles_x1c", product_sql(100, 800, 800))
def _(spark, sf):
    a, b, r, s = _sparse(spark, sf, 100, 800, 800)
    out = sparse.to_cells(sparse.resident_multiply(a, b, r, s, 5, _Q), _Q)
    return out.select(F.col("row").alias("i"), F.col("col").alias("j"), F.round("val").cast("bigint").alias("c"))


@query(
    "sparse_volume_x1c",
    f"""WITH a AS (SELECT DISTINCT i // {_Q} AS bi, k // {_Q} AS bk FROM ({matrices.a_sql(100, 800)})), b AS (SELECT DISTINCT k // {_Q} AS bk, j // {_Q} AS bj FROM ({matrices.b_sql(800, 800)}))
SELECT 'A' AS kind, (count(*) * 8)::BIGINT AS tiles FROM a WHERE bk IN (SELECT bk FROM b) UNION ALL SELECT 'B', count(*)::BIGINT FROM b WHERE bk IN (SELECT bk FROM a)""",
)
def _(spark, sf):
    """Result of 5 x 40 tiles, side 5: 1 chunk row, 8 chunk columns."""
    a, b, r, s = _sparse(spark, sf, 100, 800, 800)
    return sparse.volume(a, b, r, s, 5)


@query(
    "sparse_terms",
    """WITH w AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS term FROM documents), n AS (SELECT doc_id, term, count(*) AS n FROM w WHERE term <> '' GROUP BY 1, 2),
x AS (SELECT (doc_id % 50)::BIGINT AS i, length(term)::BIGINT AS k, sum(n) AS v FROM n GROUP BY 1, 2)
SELECT a.i, b.i AS j, sum(a.v * b.v)::BIGINT AS c FROM x a JOIN x b ON a.k = b.k GROUP BY 1, 2""",
)
def _(spark, sf):
    """Words by length in fifty groups of documents, and the groups' products: a sparse matrix times its transpose."""
    terms = matrices.terms(table(spark, sf, "documents"), "doc_id")
    x = terms.groupBy((F.col("id") % 50).alias("row"), F.length("term").cast("bigint").alias("col")).agg(F.sum("n").alias("val"))
    scratch = Scratch(spark, "terms")
    a = scratch.save(sparse.to_sparse(x, 8), "a")
    b = scratch.save(sparse.to_sparse(tiles.transpose(x), 8), "b")
    out = sparse.to_cells(sparse.resident_multiply(a, b, 7, 7, 4, 8), 8)
    return out.select(F.col("row").alias("i"), F.col("col").alias("j"), F.round("val").cast("bigint").alias("c"))


# ---- matrix expressions ----------------------------------------------------------------------------------------------------------------


def _leaves(spark: SparkSession, sf: str) -> tuple[expr.Expr, expr.Expr, expr.Expr]:
    a = expr.Matrix(100, 100, "A", matrices.left(spark, sf, 100, 100).toDF("row", "col", "val"))
    b = expr.Matrix(100, 800, "B", matrices.right(spark, sf, 100, 800).toDF("row", "col", "val"))
    e = expr.Matrix(800, 1, "v", spark.range(800).select(F.col("id").alias("row"), F.lit(0).cast("bigint").alias("col"), (F.col("id") % 7).alias("val")))
    return a, b, e


@query("expr_row_sums", f"SELECT i AS row, 0::BIGINT AS col, sum(c)::BIGINT AS val FROM ({product_sql(100, 100, 800)}) GROUP BY i")
def _(spark, sf):
    """Row sums of a product, without the product."""
    a, b, _ = _leaves(spark, sf)
    return expr.lower(expr.rewrite((a @ b).row_sums()))


@query("expr_trace", f"SELECT 0::BIGINT AS row, 0::BIGINT AS col, sum(a.v * b.v)::BIGINT AS val FROM ({matrices.a_sql(100, 100)}) a JOIN ({matrices.a_sql(100, 100)}) b ON a.k = b.i AND a.i = b.k")
def _(spark, sf):
    """Trace of A A as the sum of a Hadamard product."""
    a, _, _ = _leaves(spark, sf)
    return expr.lower(expr.rewrite((a @ a).trace()))


@query("expr_chain", f"SELECT i AS row, 0::BIGINT AS col, sum(c * (j % 7))::BIGINT AS val FROM ({product_sql(100, 100, 800)}) GROUP BY i")
def _(spark, sf):
    """(A B) v, bracketed anew as A (B v)."""
    a, b, v = _leaves(spark, sf)
    return expr.lower(expr.rewrite((a @ b) @ v))


@query("expr_transposed", f"SELECT j AS row, i AS col, c AS val FROM ({product_sql(100, 100, 800)})")
def _(spark, sf):
    a, b, _ = _leaves(spark, sf)
    return expr.lower(expr.rewrite((a @ b).T))


@query(
    "expr_plans",
    """SELECT * FROM (VALUES ('rowsums', 'RowSums((A B))', '(A RowSums(B))', 8000000::BIGINT, 10000::BIGINT), ('colsums', 'ColSums((A B))', '(ColSums(A) B)', 8000000, 80000),
('trace', 'Trace((A A))', 'Total((A o A''))', 1000000, 10000), ('chain', '((A B) v)', '(A (B v))', 8080000, 90000), ('transposed', '(A B)''', '(B'' A'')', 8000000, 8000000),
('twice', 'A''''', 'A', 0, 0), ('sum', 'RowSums(((A B) + B))', '((A RowSums(B)) + RowSums(B))', 8000000, 10000)) t(name, written, rewritten, before, after)""",
)
def _(spark, sf):
    """What the rewriter does, with dense multiplications before and after."""
    a, b, v = _leaves(spark, sf)
    trees = {"rowsums": (a @ b).row_sums(), "colsums": (a @ b).col_sums(), "trace": (a @ a).trace(), "chain": (a @ b) @ v, "transposed": (a @ b).T, "twice": a.T.T, "sum": (a @ b + b).row_sums()}
    rows = [(n, str(e), str(x := expr.rewrite(e)), expr.multiplications(e), expr.multiplications(x)) for n, e in trees.items()]
    return spark.createDataFrame(rows, "name string, written string, rewritten string, before bigint, after bigint")


# ---- user functions --------------------------------------------------------------------------------------------------------------------


def _tiled(spark: SparkSession, sf: str, q: int = 10) -> DataFrame:
    return tiles.to_tiles(matrices.left(spark, sf, 100, 100).toDF("row", "col", "val"), q)


_CELLS = f"SELECT i // 10 AS bi, k // 10 AS bj, i % 10 * 10 + k % 10 AS n, v FROM ({matrices.a_sql(100, 100)})"


@query("udf_dot", f"SELECT bi::INTEGER AS bi, bj::INTEGER AS bj, sum(v * v)::DOUBLE AS dot FROM ({_CELLS}) GROUP BY 1, 2")
def _(spark, sf):
    return _tiled(spark, sf).select("bi", "bj", udfs.dot_tile("tile", "tile").alias("dot"))


@query("dot_builtin", f"SELECT bi::INTEGER AS bi, bj::INTEGER AS bj, sum(v * v)::DOUBLE AS dot FROM ({_CELLS}) GROUP BY 1, 2")
def _(spark, sf):
    return _tiled(spark, sf).select("bi", "bj", udfs.dot_column("tile", "tile").alias("dot"))


@query(
    "udf_gemm",
    f"WITH x AS ({_CELLS}) SELECT a.bi::INTEGER AS bi, a.bj::INTEGER AS bj, sum(a.v * b.v)::DOUBLE AS total FROM x a JOIN x b ON a.bi = b.bi AND a.bj = b.bj AND a.n % 10 = b.n // 10 GROUP BY 1, 2",
)
def _(spark, sf):
    """Total of each tile's square."""
    squares = _tiled(spark, sf).select("bi", "bj", udfs.gemm_tile("tile", "tile").alias("tile"))
    return squares.select("bi", "bj", F.aggregate("tile", F.lit(0.0), lambda s, x: s + x).alias("total"))


_SUMS = f"SELECT bi::INTEGER AS bi, n::INTEGER AS n, sum(v)::DOUBLE AS x FROM ({_CELLS}) GROUP BY 1, 2 HAVING sum(v) <> 0"


@query("udaf_tile_sum", _SUMS)
def _(spark, sf):
    sums = _tiled(spark, sf).groupBy("bi").agg(udfs.tile_sum_group("tile").alias("tile"))  # ten tiles a group
    return sums.select("bi", F.posexplode("tile").alias("n", "x")).filter("x <> 0")


@query("tile_sum_builtin", _SUMS)
def _(spark, sf):
    return udfs.tile_sum(_tiled(spark, sf), ["bi"]).select("bi", F.posexplode("tile").alias("n", "x")).filter("x <> 0")


@query("udtf_schedule")
def _(spark, sf):
    """Messages of a scenario by worker, through the table function in SQL."""
    udfs.register(spark)
    return spark.sql(
        "SELECT p.policy, s.worker_id, count(*) AS messages, sum(s.tiles) AS tiles, max(s.finish) AS finish FROM VALUES ('rr_all'), ('rr_selected') p(policy),"
        " LATERAL schedule_steps(p.policy, 8, 10, 32, 4, 100, 7, 96) s GROUP BY p.policy, s.worker_id"
    )


# side 8: one chunk row of four chunk columns; a worker of rr_all has one column, rr_selected one worker for all
ORACLES["udtf_schedule"] = """WITH x AS (SELECT 'rr_all' AS policy, unnest(range(1, 5)) AS worker_id, 1 AS chunks UNION ALL SELECT 'rr_selected', 1, 4)
SELECT policy, worker_id::INTEGER AS worker_id, (chunks * 12)::BIGINT AS messages, (chunks * (2 * 64 + 10 * 16))::BIGINT AS tiles,
(CASE policy WHEN 'rr_selected' THEN 4 * (6400 + 10 * 1600 + 448 + 6400) ELSE 4 * 6400 + 10 * 4 * 1600 + worker_id * 6400 END)::BIGINT AS finish FROM x"""


@query("sql_functions", "SELECT m, (floor(sqrt(m + 4)) - 2)::BIGINT AS overlap, (floor(sqrt(m + 1)) - 1)::BIGINT AS plain, (2 * 80000 + 10000 * ceil(800 / (floor(sqrt(m + 4)) - 2)) + 80000 * ceil(100 / (floor(sqrt(m + 4)) - 2)))::BIGINT AS tiles FROM (SELECT unnest([21, 2703, 5242, 10485])::BIGINT AS m)")
def _(spark, sf):
    udfs.register(spark)
    return spark.sql("SELECT m, side_overlap(m) AS overlap, side_plain(m) AS plain, problem_volume(100, 100, 800, side_overlap(m)) AS tiles FROM VALUES (21L), (2703L), (5242L), (10485L) t(m)")


# ---- formats and samples ---------------------------------------------------------------------------------------------------------------


@query("tiles_format", f"SELECT i AS row, k AS col, v::DOUBLE AS val FROM ({matrices.a_sql(100, 100)}) WHERE v <> 0")
def _(spark, sf):
    """A matrix written as binary tile files and read again."""
    tilefile.register(spark)
    path = Scratch(spark, "tilefiles").base
    _tiled(spark, sf).write.format("tiles").option("q", 10).mode("append").save(path)
    return tiles.to_cells(spark.read.format("tiles").option("q", 10).load(path), 10)


def _again(spark: SparkSession, df: DataFrame, kind: str, **options: str) -> DataFrame:
    path = f"{Scratch(spark, kind).base}/{kind}"
    df.write.format(kind).options(**options).mode("overwrite").save(path)
    return spark.read.format(kind).options(**options).schema(df.schema).load(path)


for _kind, _options in {"csv": {"header": "true"}, "json": {}, "orc": {}}.items():
    query(f"{_kind}_format", f"SELECT i, k, v::BIGINT AS v FROM ({matrices.a_sql(100, 100)})")(lambda spark, sf, kind=_kind, options=_options: _again(spark, matrices.left(spark, sf, 100, 100), kind, **options))


@query("stored_stripes", f"SELECT i, k, v::BIGINT AS v FROM ({matrices.a_sql(100, 100)}) WHERE i // 20 = 3 AND k < 30")
def _(spark, sf):
    """A matrix stored by row stripe, rows sorted inside: a slice reads one folder, and the files' statistics skip the rest."""
    path = f"{Scratch(spark, 'stripes').base}/a"
    rows = matrices.left(spark, sf, 100, 100).withColumn("ci", F.floor(F.col("i") / 20).cast("int"))
    rows.repartition("ci").sortWithinPartitions("ci", "k").write.mode("overwrite").partitionBy("ci").parquet(path)
    return spark.read.parquet(path).filter("ci = 3 AND k < 30").select("i", "k", "v")


@query("sampling")
def _(spark, sf):
    """A matrix's cells estimated from a sample of lines, uniform and by stratum, beside the true count."""
    lines = table(spark, sf, "lineitem").select("l_returnflag")
    parts = {"all": lines, "uniform": lines.sample(0.1, 7), "strata": lines.sampleBy("l_returnflag", {"A": 0.2, "N": 0.1, "R": 0.2}, 7)}
    out = None
    for name, df in parts.items():
        one = df.groupBy("l_returnflag").agg(F.count("*").alias("n")).select(F.lit(name).alias("sample"), "l_returnflag", "n")
        out = one if out is None else out.union(one)
    return out


# ---- joins and sets --------------------------------------------------------------------------------------------------------------------


@query(
    "full_outer_tiles",
    f"SELECT coalesce(a.i, b.i) AS i, coalesce(a.k, b.k) AS k, (coalesce(a.v, 0) - coalesce(b.v, 0))::BIGINT AS v FROM ({matrices.a_sql(100, 100)}) a FULL JOIN (SELECT k AS i, j AS k, u AS v FROM ({matrices.b_sql(100, 100)})) b ON a.i = b.i AND a.k = b.k",
)
def _(spark, sf):
    """A - B with cells that either has."""
    a, b = matrices.left(spark, sf, 100, 100), matrices.right(spark, sf, 100, 100).toDF("i", "k", "x")
    zero = F.lit(0).cast("bigint")
    return a.join(b, ["i", "k"], "full").select("i", "k", (F.coalesce("v", zero) - F.coalesce("x", zero)).alias("v"))


@query(
    "set_ops_cells",
    f"WITH a AS (SELECT i, k FROM ({matrices.a_sql(100, 100)})), b AS (SELECT k AS i, j AS k FROM ({matrices.b_sql(100, 100)})) SELECT 'both' AS part, count(*)::BIGINT AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'left', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)",
)
def _(spark, sf):
    a, b = matrices.left(spark, sf, 100, 100).select("i", "k"), matrices.right(spark, sf, 100, 100).select(F.col("k").alias("i"), F.col("j").alias("k"))
    out = None
    for name, df in {"both": a.intersect(b), "left": a.exceptAll(b), "either": a.union(b).distinct()}.items():
        one = df.agg(F.count("*").alias("n")).select(F.lit(name).alias("part"), "n")
        out = one if out is None else out.union(one)
    return out


@query(
    "theta_join",
    """WITH s AS (SELECT n_regionkey AS region, n_nationkey AS nation, sum(round(s_acctbal * 100))::BIGINT AS cents FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1, 2)
SELECT a.region, a.nation, count(*)::BIGINT AS richer FROM s a JOIN s b ON b.cents > a.cents AND b.region <> a.region GROUP BY 1, 2""",
)
def _(spark, sf):
    """Nations of other regions with more balance: an inequality join of a table with one row per nation, so a nested loop over a bounded side."""
    nation = table(spark, sf, "nation").select("n_nationkey", F.col("n_regionkey").alias("region"))
    own = table(spark, sf, "supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey"))
    own = own.groupBy("region", F.col("n_nationkey").alias("nation")).agg(F.sum(F.round(F.col("s_acctbal") * 100).cast("bigint")).alias("cents"))
    other = own.select(F.col("region").alias("r2"), F.col("cents").alias("c2"))
    return own.join(F.broadcast(other), (F.col("c2") > F.col("cents")) & (F.col("r2") != F.col("region"))).groupBy("region", "nation").agg(F.count("*").alias("richer"))


@query("percentiles", "SELECT l_returnflag AS flag, quantile_disc(l_quantity, 0.25)::DOUBLE AS q1, median(l_quantity)::DOUBLE AS mid, max(l_partkey)::BIGINT AS top, min_by(l_partkey, l_partkey * 8 + l_linenumber)::BIGINT AS first FROM lineitem GROUP BY 1")
def _(spark, sf):
    lines = table(spark, sf, "lineitem")
    low = F.min_by("l_partkey", F.col("l_partkey") * 8 + F.col("l_linenumber"))
    return lines.groupBy(F.col("l_returnflag").alias("flag")).agg(
        F.expr("percentile_disc(0.25) WITHIN GROUP (ORDER BY l_quantity)").alias("q1"), F.median("l_quantity").alias("mid"), F.max("l_partkey").alias("top"), low.alias("first")
    )


@query("map_scalars", "SELECT n_regionkey AS region, string_agg(upper(substr(n_name, 1, 3)) || ':' || n_nationkey, ',' ORDER BY n_nationkey) AS codes, max(n_nationkey)::BIGINT AS top FROM nation GROUP BY 1")
def _(spark, sf):
    """A map per region from nation to its short name, and back to text."""
    pairs = F.sort_array(F.collect_list(F.struct("n_nationkey", F.upper(F.substring("n_name", 1, 3)).alias("code"))))  # nations of a region
    one = table(spark, sf, "nation").groupBy(F.col("n_regionkey").alias("region")).agg(F.map_from_entries(pairs).alias("m"))
    text = F.array_join(F.transform(F.map_entries("m"), lambda x: F.concat_ws(":", x["value"], x["key"].cast("string"))), ",")
    return one.select("region", text.alias("codes"), F.array_max(F.map_keys("m")).cast("bigint").alias("top"))


@query("stream_platform", "SELECT (user_id % 3 + 1)::INTEGER AS worker_id, event_type, count(*)::BIGINT AS n, (count(*) * CASE user_id % 3 WHEN 0 THEN 2 WHEN 1 THEN 3 ELSE 1 END)::BIGINT AS work FROM events GROUP BY user_id % 3, event_type")
def _(spark, sf):
    """A stream of events joined with a static platform, and the work that it brings each worker."""
    rows = panels.finish(panels.with_platform(panels.stream(spark, sf), platforms.literal(spark, platforms.THREE), 3).select("worker_id", "event_type", "w"))
    return rows.groupBy("worker_id", "event_type").agg(F.count("*").alias("n"), F.sum("w").alias("work"))


@query("lu_solve", f"SELECT i::BIGINT AS row, (i % 5 + 1)::BIGINT AS x FROM ({matrices.TRADE_SQL}) GROUP BY i")
def _(spark, sf):
    """M x = y for a known x: the factors give x back."""
    m = matrices.trade(spark, sf).toDF("row", "col", "val").select(F.col("row").cast("bigint").alias("row"), F.col("col").cast("bigint").alias("col"), "val")
    y = tiles.matvec(m, m.select(F.col("row").alias("k")).distinct().withColumn("x", F.col("k") % 5 + 1))
    solved = lu.solve(m, y, 25, 5, Scratch(spark, "solve"))
    return solved.join(m.select("row").distinct(), "row", "left_semi").select("row", F.round("x").cast("bigint").alias("x"))


# ---- planners against SQL and against each other ---------------------------------------------------------------------------------------

for _rule in ("global2", "global2_receding", "local2", "local2_receding"):
    ORACLES[f"lookahead_{_rule}_t2"] = select.pair_sql(_T2, 60, _rule.startswith("local"), _rule.endswith("receding"))

_LONG = {"global": select.selection_sql("FROM own", 2000), "local": select.selection_sql("FROM own", 2000, True), "global2": select.pair_sql("FROM own", 2000), "global2_receding": select.pair_sql("FROM own", 2000, recede=True)}
ORACLES["asymptotic_t2"] = f"WITH own AS MATERIALIZED ({platforms.orders_sql(2, 3)}) " + " UNION ALL ".join(
    f"SELECT '{rule}' AS rule, platform_id, round(arg_max(work / finish::DOUBLE, step), 3)::DOUBLE AS ratio FROM ({sql}) GROUP BY platform_id" for rule, sql in _LONG.items()
)

_REGIONS = f"SELECT platform_id, worker_id, c, w, g FROM ({platforms.REGIONS_SQL})"
ORACLES["preallocate_regions"] = select.preallocate_sql(_REGIONS, 400, 20, 4, 60)
ORACLES["alternating_grid"] = f"""WITH x AS ({drawn_sql(ONE_WORKER)}),
m AS (SELECT *, unnest(range(1, r + s + 1)) AS n FROM x),
t AS (SELECT *, CASE WHEN n <= 2 * least(r, s) THEN n // 2 ELSE least(r, s) END AS fresh FROM m),
u AS (SELECT *, c * n + w * sum(fresh) OVER (PARTITION BY c, w, r, s ORDER BY n ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS last FROM t)
SELECT c, w, r, s, lines, max(last) FILTER (fresh > 0)::BIGINT AS makespan FROM u GROUP BY ALL"""

ORACLES["buffer_demand_t1"] = f"""WITH x AS (SELECT *, 2.0::DOUBLE * c / (g * w) AS load FROM ({platforms.orders_sql(16, 4)}) WHERE g > 0),
u AS (SELECT *, sum(load) OVER (PARTITION BY platform_id ORDER BY 2.0::DOUBLE * c / g, worker_id ROWS UNBOUNDED PRECEDING) AS upto FROM x),
y AS (SELECT *, max(2 * c * g) OVER (PARTITION BY platform_id) AS wait FROM u WHERE 1.0 - (upto - load) > 0), z AS (SELECT *, 2 * g * ceil(wait / (w * g * g)) + g * g + 2 * g AS need FROM y)
SELECT platform_id, worker_id, m, g, wait::BIGINT AS wait, need::BIGINT AS need, need <= m AS fits FROM z"""
ORACLES["lu_plan_regions"] = lu.plan_sql(_REGIONS, 60)

_COUNTS = " UNION ALL ".join(
    f"SELECT '{n}' AS shape, {r}::BIGINT AS r, {t}::BIGINT AS t, {s}::BIGINT AS s, (SELECT count(*) FROM ({matrices.a_sql(r, t)})) AS a, (SELECT count(*) FROM ({matrices.b_sql(t, s)})) AS b" for n, (r, t, s) in SHAPES.items()
)
# memory 10,485: sides 100, 59 and 45; eight workers in a row, in a grid of 2 x 4, in a square of 2 x 2, and in three columns of 3, 3 and 2 rectangles.
# The parts of a result of r x s are too large for a worker's memory unless r * s <= 8 * 10485; all of it never fits one worker, nor does B.
ORACLES["kernel_choice"] = f"""WITH x AS ({_COUNTS}),
y AS (SELECT shape, unnest([100, 59, 45]) AS g, unnest(['resident', 'third', 'fifth']) AS kernel, r, t, s, a, b FROM x),
q AS (SELECT shape, r, s, a, b, unnest([0, 3, 6, 1, 4, 7, 2, 5]) AS n, unnest([0, 1, 2, 0, 1, 2, 0, 1]) AS nth, unnest([3, 3, 3, 3, 3, 3, 2, 2]) AS many, unnest([0, 0, 0, 3, 3, 3, 6, 6]) AS past FROM x),
z AS (SELECT shape, kernel, 2 * r * s + a * ((s + g - 1) // g) + b * ((r + g - 1) // g) AS moved FROM y
  UNION ALL SELECT shape, 'inner_join', a + b + least(a * b // t, r * s * t) FROM x
  UNION ALL SELECT shape, 'broadcast', 8 * b + least(a * b // t, r * s * t) FROM x WHERE b <= 10485
  UNION ALL SELECT shape, 'inner_split', a + b + 8 * r * s FROM x WHERE r * s <= 10485
  UNION ALL SELECT shape, 'slabs', 2 * r * s + a + 8 * b FROM x WHERE r * s <= 8 * 10485
  UNION ALL SELECT shape, k, 2 * r * s + 4 * a + 2 * b FROM x, (VALUES ('grid'), ('weighted_grid')) v(k) WHERE r * s <= 8 * 10485
  UNION ALL SELECT shape, 'shifted', 2 * r * s + 2 * a + 2 * b FROM x WHERE r * s <= 4 * 10485
  UNION ALL SELECT shape, 'rectangles', 2 * any_value(r) * any_value(s) + sum(a * (r * (nth + 1) // many - r * nth // many) // r + b * (s * (past + many) // 8 - s * past // 8) // s)
    FROM q WHERE r * s <= 8 * 10485 GROUP BY shape)
SELECT shape, arg_min(kernel, (moved, kernel)) AS kernel FROM z GROUP BY shape"""


@query(
    "waits_t2",
    f"""WITH tr AS ({select.selection_sql(_T2, 200, True)}), x AS (SELECT tr.*, p.g, p.g * p.g * p.w AS panel, tr.finish - lag(tr.finish) OVER (PARTITION BY tr.worker_id ORDER BY step) AS gap FROM tr JOIN ({_T2}) p ON p.worker_id = tr.worker_id)
SELECT platform_id, worker_id, count(*)::BIGINT AS messages, coalesce(max(gap), 0)::BIGINT AS longest, count(*) FILTER (gap > panel)::BIGINT AS starved,
(g * g + 2 * g * (1 + ceil(greatest(coalesce(max(gap), 0), 1) / panel)))::BIGINT AS need, (g * g + 2 * g * (1 + ceil(greatest(coalesce(max(gap), 0), 1) / panel))) <= g * g + 4 * g AS fits FROM x GROUP BY platform_id, worker_id, g, panel""",
)
def _(spark, sf):
    """Simulated waits of the local rule's workers, with double buffers."""
    platform = platforms.literal(spark, platforms.THREE).withColumn("m", F.col("g") * F.col("g") + 4 * F.col("g"))
    return select.waits(select.fold(select.as_rows(platform), 200, "local"), platform)


@query("rr_closed_form", """WITH x AS (SELECT * FROM (VALUES (100, 100, 800, 10485, 100, 4), (200, 200, 1600, 10485, 100, 4), (200, 200, 800, 10485, 100, 4), (200, 200, 800, 2703, 50, 2)) t(r, t, s, m, g, p)),
y AS (SELECT *, unnest(range(0, p)) AS n FROM x),
z AS (SELECT r, t, s, m, g, p, max(p * g * g * 100 + 2 * g * 100 * t * p + greatest(0, g * g * 7 - 2 * g * 100 * (p - 1 - n)) + (p - n) * g * g * 100) AS turn FROM y GROUP BY ALL)
SELECT r::BIGINT AS r, t::BIGINT AS t, s::BIGINT AS s, m::BIGINT AS m, (turn * (r // g) * (s // (g * p)))::BIGINT AS makespan FROM z""")
def _(spark, sf):
    """Simulated makespans of the round-robin with a bound port; SQL has the closed form: rounds of squares, panels, and returns that wait for the last panel."""
    shapes = ((100, 100, 800, 10485), (200, 200, 1600, 10485), (200, 200, 800, 10485), (200, 200, 800, 2703))
    cases = schedulers.scenarios(spark, shapes, ("rr_selected",))
    out = schedulers.simulate(cases).select("scenario_id", "makespan")
    own = cases.select("scenario_id", *(F.col(k).cast("bigint") for k in ("r", "t", "s")), F.element_at("platform", 1)["m"].cast("bigint").alias("m"))
    return own.join(out, "scenario_id").select("r", "t", "s", "m", "makespan")


@query("makespan_bounds", "SELECT 0::BIGINT AS below")
def _(spark, sf):
    """Scenarios whose makespan beats the port's or the workers' least time: expected none."""
    cases = schedulers.scenarios(spark, schedulers.SET_ONE + schedulers.SET_MEMORY, tuple(schedulers.POLICIES))
    runs = schedulers.simulate(cases)
    own = cases.select("scenario_id", F.size("platform").alias("p"), F.element_at("platform", 1)["c"].alias("c"), F.element_at("platform", 1)["w"].alias("w")).distinct()
    work = (F.col("updates") * F.col("w") / F.col("p")).cast("double")
    return runs.join(own, "scenario_id").agg(F.sum(F.when((F.col("makespan") < F.col("tiles") * F.col("c")) | (F.col("makespan") < work), 1).otherwise(0)).alias("below"))


@query("volume_against_bound", "SELECT 0::BIGINT AS below")
def _(spark, sf):
    """Layouts and shapes whose volume is below the proven bound: expected none."""
    rows = spark.createDataFrame([(*x, m) for x in ((100, 100, 800), (200, 200, 1600), (100, 800, 800), (200, 200, 800)) for m in (21, 2703, 5242, 10485)], "r bigint, t bigint, s bigint, m bigint")
    u = F.col("r") * F.col("t") * F.col("s")
    each = [bounds.problem_volume(F.col("r"), F.col("t"), F.col("s"), f(F.col("m"))) < bounds.lower_bound_product(F.col("m")) * u for f in layout.SIDES.values()]
    return rows.agg(sum((F.sum(F.when(x, 1).otherwise(0)) for x in each[1:]), F.sum(F.when(each[0], 1).otherwise(0))).alias("below"))


@query(
    "port_gaps",
    f"WITH tr AS ({select.selection_sql(_T2, 60)}) SELECT step, worker_id, (finish - coalesce(lag(finish) OVER (ORDER BY step), 0))::BIGINT AS gap, count(*) OVER (PARTITION BY worker_id ORDER BY step)::BIGINT AS nth, ntile(4) OVER (ORDER BY step)::INTEGER AS quarter FROM tr",
)
def _(spark, sf):
    """Time between ends of messages, by step."""
    rows = select.trace(select.fold(select.as_rows(platforms.literal(spark, platforms.THREE)), 60, "global"))
    by, own = Window.partitionBy("platform_id").orderBy("step"), Window.partitionBy("platform_id", "worker_id").orderBy("step")
    return rows.select("step", "worker_id", (F.col("finish") - F.coalesce(F.lag("finish").over(by), F.lit(0))).alias("gap"), F.count("*").over(own).alias("nth"), F.ntile(4).over(by).alias("quarter"))
