"""The experiment workloads and operator queries on the given tables; each entry of QUERIES has its SQL in ORACLES where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilestar.functions import bounds, layout
from tilestar.operators import lu, multiply, nearest, tiles
from tilestar.plans import enrol, execute, onepass, schedulers, select
from tilestar.runtime import Scratch, bucketed, table
from tilestar.sources import matrices, platforms
from tilestar.streaming import panels

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# ---- cases from the lines of lineitem ----------------------------------------------------------------------------------------------------

_KEYED = "l_orderkey IS NOT NULL AND l_partkey IS NOT NULL AND l_suppkey IS NOT NULL"


def _drawn(spark: SparkSession, sf: str, case: dict[str, str]) -> DataFrame:
    """The differing cases that the lines of lineitem draw, by an expression over its keys for each column, with the number of lines that draw each."""
    rows = table(spark, sf, "lineitem").filter(_KEYED).select(*(F.expr(x).cast("bigint").alias(k) for k, x in case.items()))
    return rows.groupBy(*case).agg(F.count("*").alias("lines"))


def drawn_sql(case: dict[str, str]) -> str:
    return f"SELECT {', '.join(f'({x})::BIGINT AS {k}' for k, x in case.items())}, count(*)::BIGINT AS lines FROM lineitem WHERE {_KEYED} GROUP BY ALL"


# ---- products of the experiment sets ---------------------------------------------------------------------------------------------------

#: Shapes (r, t, s) of the sets; the side is that of 10,485 double-buffered tiles.
SHAPES = {"x1a": (100, 100, 800), "x1b": (200, 200, 1600), "x1c": (100, 800, 800), "x3": (200, 200, 800)}
SIDE = 100
SPEEDS = [5, 3, 3, 2, 1]


def product_sql(r: int, t: int, s: int, start: bool = False) -> str:
    body = f"SELECT i, j, v * u AS x FROM ({matrices.a_sql(r, t)}) a JOIN ({matrices.b_sql(t, s)}) b ON a.k = b.k"
    if start:
        body += f" UNION ALL SELECT (l_orderkey + l_suppkey) % {r}, l_orderkey % {s}, 1 FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders)"
    return f"SELECT i, j, sum(x)::BIGINT AS c FROM ({body}) GROUP BY i, j"


def _operands(spark: SparkSession, sf: str, shape: str) -> tuple[DataFrame, DataFrame, int, int, int]:
    r, t, s = SHAPES[shape]
    return matrices.left(spark, sf, r, t), matrices.right(spark, sf, t, s), r, t, s


def _kernel(name: str, shape: str, f: Callable[[DataFrame, DataFrame, int, int, int], DataFrame]) -> None:
    QUERIES[name] = lambda spark, sf: f(*_operands(spark, sf, shape))
    ORACLES[name] = product_sql(*SHAPES[shape])


for _shape in SHAPES:
    _kernel(f"resident_sql_{_shape}", _shape, lambda a, b, r, t, s: multiply.chunked(a, b, multiply.Cut.squares(r, s, SIDE)))
_kernel("resident_small_memory_x3", "x3", lambda a, b, r, t, s: multiply.chunked(a, b, multiply.Cut.squares(r, s, 50)))
_kernel("split3_x1a", "x1a", lambda a, b, r, t, s: multiply.split(a, b, r, s, 10485, 3))
_kernel("split5_x1a", "x1a", lambda a, b, r, t, s: multiply.split(a, b, r, s, 10485, 5))
_kernel("inner_join_x1a", "x1a", lambda a, b, r, t, s: multiply.inner_join(a, b))
_kernel("inner_join_salted_x1a", "x1a", lambda a, b, r, t, s: multiply.inner_join(a, b, salt=4))
_kernel("broadcast_x1a", "x1a", lambda a, b, r, t, s: multiply.broadcast(a, b))
_kernel("slab_x1a", "x1a", lambda a, b, r, t, s: multiply.slabs(a, b, r, SPEEDS))
_kernel("grid_x1a", "x1a", lambda a, b, r, t, s: multiply.grid(a, b, r, s, 2, 4))
_kernel("weighted_grid_x1a", "x1a", lambda a, b, r, t, s: multiply.weighted_grid(a, b, r, s, [3, 1], [4, 2, 1, 1]))
_kernel("shift_x1a", "x1a", lambda a, b, r, t, s: multiply.shifted(a, b, r, t, s, 3))
_kernel("rectangles_x1a", "x1a", lambda a, b, r, t, s: multiply.rectangles(a, b, r, s, SPEEDS))
_kernel("inner_split_x1a", "x1a", lambda a, b, r, t, s: multiply.inner_split(a, b, 8))


@query("resident_tiles_x1a", product_sql(100, 100, 800))
def _(spark, sf):
    a, b, r, _t, s = _operands(spark, sf, "x1a")
    q = 4
    left, right = tiles.to_tiles(a.toDF("row", "col", "val"), q), tiles.to_tiles(b.toDF("row", "col", "val"), q)
    out = tiles.to_cells(tiles.resident_multiply(left, right, -(-r // q), -(-s // q), SIDE // q, q), q)
    return out.select(F.col("row").alias("i"), F.col("col").alias("j"), F.round("val").cast("bigint").alias("c"))


@query("tile_size_8_x1a", product_sql(100, 100, 800))
def _(spark, sf):
    a, b, r, _t, s = _operands(spark, sf, "x1a")
    q = 8
    left, right = tiles.to_tiles(a.toDF("row", "col", "val"), q), tiles.to_tiles(b.toDF("row", "col", "val"), q)
    out = tiles.to_cells(tiles.resident_multiply(left, right, -(-r // q), -(-s // q), max(1, SIDE // q), q), q)
    return out.select(F.col("row").alias("i"), F.col("col").alias("j"), F.round("val").cast("bigint").alias("c"))


@query("accumulate_c0", product_sql(100, 100, 800, start=True))
def _(spark, sf):
    a, b, r, _t, s = _operands(spark, sf, "x1a")
    return multiply.chunked(a, b, multiply.Cut.squares(r, s, SIDE), matrices.start(spark, sf, r, s))


@query("kernels_agree", "SELECT 0::BIGINT AS differing")
def _(spark, sf):
    """Set difference, both ways, of two kernels' results: expected none."""
    a, b, r, _t, s = _operands(spark, sf, "x1a")
    x, y = multiply.chunked(a, b, multiply.Cut.squares(r, s, SIDE)), multiply.inner_join(a, b)
    return x.exceptAll(y).unionAll(y.exceptAll(x)).agg(F.count("*").alias("differing"))


@query("freivalds_check", "SELECT n::INTEGER AS probe, 0::BIGINT AS bad FROM range(1, 3) t(n)")
def _(spark, sf):
    a, b, r, _t, s = _operands(spark, sf, "x1a")
    return multiply.freivalds(a, b, multiply.chunked(a, b, multiply.Cut.squares(r, s, SIDE)))


@query("gram_embeddings", f"WITH e AS ({matrices.EMBED_SQL}) SELECT x.col AS row, y.col AS col, sum(x.val * y.val)::BIGINT AS val FROM e x JOIN e y ON x.row = y.row GROUP BY 1, 2")
def _(spark, sf):
    e = matrices.embeddings(spark, sf)
    left = e.select(F.col("col").alias("i"), F.col("row").alias("k"), F.col("val").alias("v"))
    right = e.select(F.col("row").alias("k"), F.col("col").alias("j"), F.col("val").alias("u"))
    return multiply.inner_split(left, right, 8).select(F.col("i").alias("row"), F.col("j").alias("col"), F.col("c").alias("val"))


@query("label_centroids", f"WITH e AS ({matrices.EMBED_SQL}) SELECT label, col, sum(val)::BIGINT AS total, count(*)::BIGINT AS n FROM e JOIN embeddings ON vec_id = row GROUP BY 1, 2")
def _(spark, sf):
    e = matrices.embeddings(spark, sf)
    return e.join(table(spark, sf, "embeddings").select("vec_id", "label"), F.col("row") == F.col("vec_id")).groupBy("label", "col").agg(F.sum("val").alias("total"), F.count("*").alias("n"))


@query(
    "cosine_topk",
    f"""WITH e AS ({matrices.EMBED_SQL}), d AS (SELECT x.row AS q, y.row AS id, sum(x.val * y.val)::BIGINT AS dot FROM e x JOIN e y ON x.col = y.col WHERE x.row % 50 = 0 AND x.row <> y.row GROUP BY 1, 2)
SELECT q, id, dot, rank FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY dot DESC, id)::INTEGER AS rank FROM d) WHERE rank <= 5""",
)
def _(spark, sf):
    """Product of blocks of query rows, which stay, with all rows, which pass by; only the top five of each are kept."""
    scratch = Scratch(spark, "cosine")
    rows = nearest.summed(matrices.embedding_rows(spark, sf), scratch)
    queries = scratch.save(rows.filter(F.col("id") % 50 == 0), "queries")
    return nearest.top_products(queries, rows, 5)


TERMS = "SELECT {id} AS id, term, count(*)::BIGINT AS n FROM (SELECT {id}, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS term FROM {table}) GROUP BY 1, 2"


@query(
    "term_overlap_benchmark",
    f"""WITH d AS ({TERMS.format(id='doc_id', table='documents')}), b AS ({TERMS.format(id='item_id', table='benchmark')})
SELECT d.id AS i, b.id AS j, sum(d.n * b.n)::BIGINT AS c FROM d JOIN b USING (term) GROUP BY 1, 2""",
)
def _(spark, sf):
    """Documents x terms times terms x benchmark, sparse; only the terms that many documents have are salted."""
    d = matrices.terms(table(spark, sf, "documents"), "doc_id").select(F.col("id").alias("i"), F.col("term").alias("k"), F.col("n").alias("v"))
    b = matrices.terms(table(spark, sf, "benchmark"), "item_id").select(F.col("term").alias("k"), F.col("id").alias("j"), F.col("n").alias("u"))
    return multiply.inner_join_heavy(d, b)


@query(
    "term_cooccurrence",
    f"""WITH b AS (SELECT DISTINCT id, term FROM ({TERMS.format(id='item_id', table='benchmark')})), d AS (SELECT term FROM b GROUP BY 1 HAVING count(*) >= 5)
SELECT x.term AS left_term, y.term AS right_term, count(*)::BIGINT AS c FROM b x JOIN b y ON x.id = y.id WHERE x.term < y.term AND x.term IN (SELECT term FROM d) AND y.term IN (SELECT term FROM d) GROUP BY 1, 2""",
)
def _(spark, sf):
    """Terms x items times items x terms: in how many benchmark items two terms meet, for terms of five items or more, above the diagonal."""
    own = matrices.terms(table(spark, sf, "benchmark"), "item_id").select("id", "term")
    often = own.groupBy("term").count().filter("count >= 5").select("term")
    cells = own.join(often, "term").select(F.col("term").alias("i"), F.col("id").alias("k"), F.lit(1).cast("bigint").alias("v"))
    out = multiply.inner_join(cells, cells.select("k", F.col("i").alias("j"), F.col("v").alias("u"))).filter("i < j")
    return out.select(F.col("i").alias("left_term"), F.col("j").alias("right_term"), "c")


@query(
    "label_terms",
    f"""WITH d AS ({TERMS.format(id='doc_id', table='documents')}), l AS (SELECT doc_id, 'quality' AS label, max(quality) AS x FROM labels GROUP BY 1 UNION ALL SELECT doc_id, 'toxic', max(toxic) FROM labels GROUP BY 1)
SELECT term, label, sum(n * x)::BIGINT AS c FROM d JOIN l ON d.id = l.doc_id WHERE x <> 0 GROUP BY 1, 2""",
)
def _(spark, sf):
    """Terms x documents times the tall 0/1 matrix of labels: the inner index is cut in parts, the result is small in one direction."""
    d = matrices.terms(table(spark, sf, "documents"), "doc_id").select(F.col("term").alias("i"), F.col("id").alias("k"), F.col("n").alias("v"))
    own = table(spark, sf, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    each = F.explode(F.array(*(F.struct(F.lit(c).alias("j"), F.col(c).cast("bigint").alias("u")) for c in ("quality", "toxic")))).alias("x")
    l = own.select(F.col("doc_id").alias("k"), each).select("k", "x.j", "x.u").filter("u <> 0")
    return multiply.inner_split(d, l, 8).select(F.col("i").alias("term"), F.col("j").alias("label"), "c")


def _gram_tiles(spark: SparkSession, sf: str, q: int, bytes_: int = 1 << 20) -> DataFrame:
    """E'E by tiles of side q, with the resident side that the same bytes give for that q."""
    e = matrices.embeddings(spark, sf)
    side = max(1, int((bytes_ // (8 * q * q) + 4) ** 0.5) - 2)
    n = -(-64 // q)
    rows = tiles.to_tiles(e, q)
    turned = tiles.to_tiles(e.select(F.col("col").alias("row"), F.col("row").alias("col"), "val"), q)
    out = tiles.to_cells(tiles.resident_multiply(turned, rows, n, n, min(side, n), q), q)
    return out.select("row", "col", F.round("val").cast("bigint").alias("val"))


_GRAM_SQL = f"WITH e AS ({matrices.EMBED_SQL}) SELECT * FROM (SELECT x.col AS row, y.col AS col, sum(x.val * y.val)::BIGINT AS val FROM e x JOIN e y ON x.row = y.row GROUP BY 1, 2) WHERE val <> 0"
for _q in (8, 16):
    QUERIES[f"gram_tiles_q{_q}"] = lambda spark, sf, q=_q: _gram_tiles(spark, sf, q)
    ORACLES[f"gram_tiles_q{_q}"] = _GRAM_SQL


@query("bucketed_join_x1a", product_sql(100, 100, 800))
def _(spark, sf):
    """Both operands stored in buckets of the inner index, so that their join moves nothing."""
    a, b, *_ = _operands(spark, sf, "x1a")
    return multiply.inner_join(*(bucketed(x, ["k"], 8) for x in (a, b)))


ROLES = "SELECT role AS a, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations"


@query(
    "role_power",
    f"""WITH m AS (SELECT a AS row, b AS col, count(*)::BIGINT AS val FROM ({ROLES}) WHERE b IS NOT NULL GROUP BY 1, 2)
SELECT x.row, z.col, sum(x.val * y.val * z.val)::BIGINT AS val FROM m x JOIN m y ON x.col = y.row JOIN m z ON y.col = z.row GROUP BY 1, 2""",
)
def _(spark, sf):
    nxt = F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn"))
    m = table(spark, sf, "conversations").select(F.col("role").alias("row"), nxt.alias("col")).filter("col is not null").groupBy("row", "col").agg(F.count("*").alias("val"))
    return tiles.power(m, 3)


HOSTS = "SELECT page_id, regexp_extract(url, '://([^/]+)', 1) AS host, regexp_extract(url, '://[^/]+/([a-z]*)', 1) AS lang FROM pages"


@query("host_links", f"WITH h AS ({HOSTS}), m AS (SELECT host, lang, count(*)::BIGINT AS n FROM h GROUP BY 1, 2) SELECT x.lang AS i, y.lang AS j, sum(x.n * y.n)::BIGINT AS c FROM m x JOIN m y USING (host) GROUP BY 1, 2")
def _(spark, sf):
    """Language x host times its transpose."""
    h = table(spark, sf, "pages").select(F.regexp_extract("url", "://([^/]+)", 1).alias("k"), F.regexp_extract("url", "://[^/]+/([a-z]*)", 1).alias("i"))
    m = h.groupBy("k", "i").agg(F.count("*").alias("v"))
    return multiply.inner_join(m, m.select("k", F.col("i").alias("j"), F.col("v").alias("u")))


@query("matrix_ops", f"""WITH e AS ({matrices.TRADE_SQL}), a AS (SELECT i AS row, j AS col, v AS val FROM e), z AS (
SELECT row, col, val FROM a UNION ALL SELECT col, row, 2 * val FROM a), s AS (SELECT row, col, sum(val) AS val FROM z GROUP BY 1, 2)
SELECT s.row, s.col, (s.val * a.val)::BIGINT AS val FROM s JOIN a ON s.row = a.row AND s.col = a.col""")
def _(spark, sf):
    """(M + 2 M^T) entrywise times M."""
    m = matrices.trade(spark, sf).toDF("row", "col", "val")
    return tiles.hadamard(tiles.add(m, tiles.transpose(m), 2), m)


# ---- volume, bounds and layouts --------------------------------------------------------------------------------------------------------

MEMORY = "(SELECT unnest([21, 2703, 5242, 10485, 1000000])::BIGINT AS m)"
ROOTS = "floor((sqrt(4 * m - 3) - 1) / 2)::BIGINT AS g_single, (floor(sqrt(m + 4)) - 2)::BIGINT AS g_overlap, (floor(sqrt(m + 1)) - 1)::BIGINT AS g_plain, floor(sqrt(m // 3))::BIGINT AS g_third, floor(sqrt(m // 5))::BIGINT AS g_fifth"


def _memory(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(m,) for m in (21, 2703, 5242, 10485, 1_000_000)], "m bigint")


@query("sides_by_memory", f"SELECT m, {ROOTS} FROM {MEMORY}")
def _(spark, sf):
    return layout.sides(_memory(spark))


_BYTES = {"mib": "32 + l_orderkey % 481", "q": "20 * (1 + l_partkey % 5)"}


@query("buffers_by_bytes", f"SELECT mib, q, lines, ((mib * 1048576) // (8 * q * q))::BIGINT AS m FROM ({drawn_sql(_BYTES)})")
def _(spark, sf):
    return _drawn(spark, sf, _BYTES).withColumn("m", layout.buffers(F.col("mib") * 1048576, F.col("q")))


_CHUNK = {"g": "1 + l_orderkey % 100", "t": "1 + l_partkey % 20", "q": "20 * (1 + l_suppkey % 4)"}


@query("chunk_volumes", f"""SELECT g, t, q, lines, (2 * g * g + 2 * g * t)::BIGINT AS volume, round(2.0::DOUBLE / t + 2.0::DOUBLE / g, 9)::DOUBLE AS per_update, round((2.0::DOUBLE / t + 2.0::DOUBLE / g) / q, 12)::DOUBLE AS per_element
FROM ({drawn_sql(_CHUNK)})""")
def _(spark, sf):
    """Tiles of a chunk's life, per tile update, and per multiply-add of elements."""
    g, t, q = F.col("g"), F.col("t"), F.col("q")
    rows = _drawn(spark, sf, _CHUNK)
    return rows.select("g", "t", "q", "lines", bounds.chunk_volume(g, t).alias("volume"), F.round(bounds.traffic_ratio(g, t), 9).alias("per_update"), F.round(bounds.traffic_ratio_elements(g, t, q), 12).alias("per_element"))


@query("lu_sides", "SELECT m, (floor(sqrt(m + 4)) - 2)::BIGINT AS g FROM (SELECT unnest([21, 2703, 5242, 10485])::BIGINT AS m)")
def _(spark, sf):
    rows = spark.createDataFrame([(m,) for m in (21, 2703, 5242, 10485)], "m bigint")
    return rows.select("m", layout.side_lu(F.col("m")).alias("g"))


@query("rectangle_sides", """WITH x AS (SELECT unnest([21, 100, 2703])::BIGINT AS m), y AS (SELECT m, r, s FROM x, (VALUES (3::BIGINT, 50::BIGINT), (100, 100)) t(r, s)),
c AS (SELECT m, r, s, a, least(s, (m - 2 * a) // (a + 2)) AS b FROM y, range(1, 1000) q(a) WHERE a <= least(r, greatest((m - 2) // 3, 1)))
SELECT m, r, s, arg_min(a, ((a + b)::DOUBLE / (a * b), a))::BIGINT AS rect_a, arg_min(b, ((a + b)::DOUBLE / (a * b), a))::BIGINT AS rect_b FROM c WHERE b >= 1 GROUP BY 1, 2, 3""")
def _(spark, sf):
    rows = spark.createDataFrame([(m, r, s) for m in (21, 100, 2703) for r, s in ((3, 50), (100, 100))], "m bigint, r bigint, s bigint")
    return layout.side_rect(rows)


_MAP = "SELECT n AS step, slot, CASE WHEN slot = 0 THEN 'A' WHEN slot <= 4 THEN 'B' ELSE 'C' END AS matrix, (CASE WHEN slot = 0 THEN (n // 4) % 4 WHEN slot <= 4 THEN n // 16 ELSE (slot - 5) // 4 END)::BIGINT AS bi, (CASE WHEN slot = 0 THEN n // 16 WHEN slot <= 4 THEN slot - 1 ELSE (slot - 5) % 4 END)::BIGINT AS bj FROM range(48) t(n), range(21) u(slot)"


@query("buffer_map", f"""WITH a AS ({matrices.a_sql(4, 3)}), b AS ({matrices.b_sql(3, 4)}),
x AS (SELECT 'A' AS matrix, i AS bi, k AS bj, 0 AS at, v AS x FROM a UNION ALL SELECT 'B', k, j, 0, u FROM b UNION ALL SELECT 'C', i, j, 16 * a.k + 4 * i + j, v * u FROM a JOIN b ON a.k = b.k)
SELECT m.step, m.slot, m.matrix, m.bi, m.bj, coalesce(sum(x.x) FILTER (x.at <= m.step), 0)::BIGINT AS held FROM ({_MAP}) m LEFT JOIN x ON x.matrix = m.matrix AND x.bi = m.bi AND x.bj = m.bj GROUP BY ALL""")
def _(spark, sf):
    """What each buffer holds at each step of a chunk of the product of lineitem's matrices."""
    return layout.buffer_contents(matrices.left(spark, sf, 4, 3), matrices.right(spark, sf, 3, 4), 4, 3)


def _volumes(spark: SparkSession) -> DataFrame:
    shapes = spark.createDataFrame([(r, t, s, m) for r, t, s in SHAPES.values() for m in (2703, 10485)], "r bigint, t bigint, s bigint, m bigint")
    each = F.explode(F.array(*(F.struct(F.lit(k).alias("layout"), f(F.col("m")).alias("g")) for k, f in layout.SIDES.items()))).alias("x")
    rows = shapes.select("r", "t", "s", "m", each).select("r", "t", "s", "m", "x.layout", "x.g")
    return rows.withColumn("tiles", bounds.problem_volume(*(F.col(c) for c in ("r", "t", "s", "g"))))


_SHAPE_SQL = "(VALUES (100::BIGINT, 100::BIGINT, 800::BIGINT), (200, 200, 1600), (100, 800, 800), (200, 200, 800)) sh(r, t, s)"
VOLUME_SQL = f"""WITH x AS (SELECT r, t, s, m, {ROOTS} FROM {_SHAPE_SQL}, (SELECT unnest([2703, 10485])::BIGINT AS m)),
y AS (SELECT r, t, s, m, u.layout, u.g FROM x, LATERAL (VALUES ('single', g_single), ('overlap', g_overlap), ('plain', g_plain), ('third', g_third), ('fifth', g_fifth)) u(layout, g))
SELECT r, t, s, m, layout, g, (2 * r * s + r * t * ((s + g - 1) // g) + t * s * ((r + g - 1) // g))::BIGINT AS tiles FROM y"""


@query("volume_by_layout", VOLUME_SQL)
def _(spark, sf):
    return _volumes(spark)


@query("volume_rollup", f"SELECT coalesce(layout, 'all') AS layout, coalesce(m, -1) AS m, sum(tiles)::BIGINT AS tiles, grouping(layout, m)::BIGINT AS level FROM ({VOLUME_SQL}) q(r, t, s, m, layout, g, tiles) GROUP BY ROLLUP (q.layout, q.m)")
def _(spark, sf):
    return _volumes(spark).rollup("layout", "m").agg(F.sum("tiles").alias("tiles"), F.grouping_id("layout", "m").alias("level")).withColumns({"layout": F.coalesce("layout", F.lit("all")), "m": F.coalesce("m", F.lit(-1))})


@query(
    "volume_measured_x1a",
    f"""WITH a AS ({matrices.a_sql(100, 100)}), b AS ({matrices.b_sql(100, 800)})
SELECT 'A' AS kind, (count(*) * 8)::BIGINT AS tiles FROM a UNION ALL SELECT 'B', count(*)::BIGINT FROM b UNION ALL SELECT 'C_in', 80000 UNION ALL SELECT 'C_out', 80000""",
)
def _(spark, sf):
    a, b, r, _t, s = _operands(spark, sf, "x1a")
    return multiply.messages(a, b, r, s, multiply.Cut.squares(r, s, SIDE))


_BUFFERS = {"m": "21 + 25 * (l_partkey * 37 % 400)"}


@query(
    "bounds_by_memory",
    f"SELECT m, lines, round(2 / sqrt(m), 9) AS achieved, round(sqrt(27 / (8.0 * m)), 9) AS product, round(sqrt(27 / (32.0 * m)), 9) AS pairwise, round(sqrt(1 / (8.0 * m)), 9) AS prior, round(sqrt(32 / 27.0), 9) AS gap FROM ({drawn_sql(_BUFFERS)})",
)
def _(spark, sf):
    m = F.col("m")
    got = {"achieved": bounds.traffic_ratio_limit(m), "product": bounds.lower_bound_product(m), "pairwise": bounds.lower_bound_pairwise(m), "prior": bounds.lower_bound_prior(m)}
    rows = _drawn(spark, sf, _BUFFERS).withColumns({k: F.round(v, 9) for k, v in got.items()})
    return rows.withColumn("gap", F.round(bounds.traffic_ratio_limit(m) / bounds.lower_bound_product(m), 9))


@query("gap_by_layout", f"SELECT r, t, s, m, layout, round(tiles / (r * t * s)::DOUBLE, 9) AS ratio, round(tiles / (r * t * s)::DOUBLE / sqrt(27 / (8.0 * m)), 9) AS gap FROM ({VOLUME_SQL})")
def _(spark, sf):
    ratio = F.col("tiles") / (F.col("r") * F.col("t") * F.col("s")).cast("double")
    return _volumes(spark).select("r", "t", "s", "m", "layout", F.round(ratio, 9).alias("ratio"), F.round(ratio / bounds.lower_bound_product(F.col("m")), 9).alias("gap"))


_SHARES = {"a": "1 + l_orderkey % 30", "b": "1 + l_partkey % 30"}


@query("bound_grid", f"""WITH y AS (SELECT a, b, least(30, 60 - a - b) AS c FROM ({drawn_sql(_SHARES)})), z AS (SELECT a, b, c, a / 30.0::DOUBLE AS u, b / 30.0::DOUBLE AS v, c / 30.0::DOUBLE AS w FROM y WHERE c >= 1),
q AS (SELECT *, 'pairwise' AS cap, least((u + v) * sqrt(w), (u + w) * sqrt(v), (v + w) * sqrt(u)) AS k FROM z UNION ALL SELECT *, 'product', sqrt(u * v * w) FROM z)
SELECT cap, max(round(k, 9)) AS k, arg_max(a, (round(k, 12), -a, -b))::BIGINT AS a, arg_max(b, (round(k, 12), -a, -b))::BIGINT AS b, arg_max(c, (round(k, 12), -a, -b))::BIGINT AS c FROM q GROUP BY cap""")
def _(spark, sf):
    return bounds.bound_grid(_drawn(spark, sf, _SHARES), 30)


@query("min_messages", "SELECT u, m, (m * floor(u / (sqrt(8 / 27.0) * m * sqrt(m))))::BIGINT AS product, (m * floor(u / (sqrt(32 / 27.0) * m * sqrt(m))))::BIGINT AS pairwise FROM (VALUES (8000000::BIGINT, 2703::BIGINT), (64000000, 10485), (1000, 10485)) t(u, m)")
def _(spark, sf):
    rows = spark.createDataFrame([(8_000_000, 2703), (64_000_000, 10485), (1000, 10485)], "u bigint, m bigint")
    u, m = F.col("u"), F.col("m")
    return rows.select("u", "m", bounds.min_messages(u, m).alias("product"), bounds.min_messages(u, m, False).alias("pairwise"))


@query("startup_loss", "SELECT round(2 * 2 * 5 / (100 * 4.5), 9)::DOUBLE AS loss, round(4 / 100.0 + 2 * 2 / (100 * 4.5), 9)::DOUBLE AS bound")
def _(spark, sf):
    c, w, g, t, p = (F.lit(x) for x in (2.0, 4.5, 4.0, 100.0, 5.0))
    loss, bound = bounds.startup_loss(c, w, g, t, p)
    return spark.range(1).select(F.round(loss, 9).alias("loss"), F.round(bound, 9).alias("bound"))


_BALANCE = 6, 6, 12, 4


@query("window_balance", bounds.balance_sql(*_BALANCE, m=21))
def _(spark, sf):
    """Held and sent tiles in every window of m messages of a single-buffer schedule, tile by tile: what is held at its start, and what moves in it."""
    return bounds.window_balance(bounds.tile_messages(spark, *_BALANCE), 21)


@query("kernel_choice")
def _(spark, sf):
    """Kernel of least volume per shape, for the operands' real densities."""
    rows = []
    for name in SHAPES:
        a, b, r, t, s = _operands(spark, sf, name)
        rows.append((name, multiply.choose_kernel(r, t, s, a.count(), b.count(), 10485)))
    return spark.createDataFrame(rows, "shape string, kernel string")



# ---- enrolment and selection -----------------------------------------------------------------------------------------------------------

_ENROL = {
    "p": "2 + 6 * (l_orderkey % 8)", "c": "1 + 33 * (l_partkey % 3)", "w": "3 + 3 * (l_suppkey % 3)",
    "g": "4 + 23 * (l_orderkey % 5)", "r": "20 + 60 * (l_partkey % 4)", "s": "100 * (1 + l_suppkey % 4)",
}


@query(
    "enrol_cases",
    f"""WITH x AS ({drawn_sql(_ENROL)}),
y AS (SELECT *, (g * w + 2 * c - 1) // (2 * c) AS want, coalesce((SELECT max(v) FROM range(1, 101) q(v) WHERE v <= g AND ((v * w + 2 * c - 1) // (2 * c)) * v * v <= r * s), 0) AS v FROM x),
z AS (SELECT *, (v * w + 2 * c - 1) // (2 * c) AS q, CASE WHEN want <= p AND want * g * g <= r * s THEN 'large' WHEN (v * w + 2 * c - 1) // (2 * c) <= p THEN 'small_c' ELSE 'short' END AS "case" FROM y)
SELECT p::BIGINT AS p, c::BIGINT AS c, w::BIGINT AS w, g::BIGINT AS g, r::BIGINT AS r, s::BIGINT AS s, lines, "case", (CASE "case" WHEN 'large' THEN want WHEN 'small_c' THEN q ELSE p END)::BIGINT AS p_used,
(CASE "case" WHEN 'large' THEN g WHEN 'small_c' THEN v ELSE greatest(least(floor(sqrt(r * s // p)), g, greatest(2 * c * p // w, 1)), 1) END)::BIGINT AS side FROM z""",
)
def _(spark, sf):
    return enrol.enrol(_drawn(spark, sf, _ENROL))


@query("enrol_smallest", """SELECT g, c, w, (SELECT min(p) FROM range(1, 1000) t(p) WHERE 2 * g * c * p >= g * g * w)::BIGINT AS p_used FROM (SELECT unnest([4, 50, 100])::BIGINT AS g), (VALUES (100::BIGINT, 7::BIGINT), (4, 9), (1, 5)) u(c, w)""")
def _(spark, sf):
    rows = spark.createDataFrame([(g, c, w) for g in (4, 50, 100) for c, w in ((100, 7), (4, 9), (1, 5))], "g bigint, c bigint, w bigint")
    return rows.withColumn("p_used", enrol.enrol_large(F.lit(1000).cast("bigint"), F.col("g"), F.col("c"), F.col("w")))


_CHUNKS = {"ci": "(l_orderkey + l_suppkey) % 200 DIV 100", "cj": "l_orderkey % 1600 DIV 100"}


@query("column_dealing", f"""WITH x AS ({drawn_sql({k: v.replace("DIV", "//") for k, v in _CHUNKS.items()})})
SELECT a.ci, b.cj, b.cj % 4 + 1 AS worker, coalesce(lines, 0)::BIGINT AS lines FROM range(2) a(ci) CROSS JOIN range(16) b(cj) LEFT JOIN x ON x.ci = a.ci AND x.cj = b.cj""")
def _(spark, sf):
    """Whole chunk columns dealt in turn, and the lines that each worker's chunks sum up."""
    dealt = multiply.assign_columns(spark, 200, 1600, 100, 4)
    return dealt.join(_drawn(spark, sf, _CHUNKS), ["ci", "cj"], "left").withColumn("lines", F.coalesce("lines", F.lit(0).cast("bigint")))


@query("enrol_machine", """SELECT g, q, least(8, ceil(g * q / 2.0::DOUBLE * flop / word))::BIGINT AS p FROM (SELECT unnest([50, 100])::BIGINT AS g), (SELECT unnest([40, 80])::BIGINT AS q), (SELECT 5.6e-10::DOUBLE AS flop, 6.4e-7::DOUBLE AS word)""")
def _(spark, sf):
    """Workers by machine constants: seconds of a multiply-add, and of eight bytes on a link of 100 Mb/s."""
    rows = spark.createDataFrame([(g, q) for g in (50, 100) for q in (40, 80)], "g bigint, q bigint")
    return rows.select("g", "q", enrol.enrol_machine(F.lit(8).cast("bigint"), F.col("g"), F.col("q"), F.lit(5.6e-10), F.lit(6.4e-7)).alias("p"))


_T2 = "SELECT 0 AS platform_id, worker_id, c::BIGINT AS c, w::BIGINT AS w, g::BIGINT AS g FROM (VALUES (1, 2, 2, 6), (2, 3, 3, 18), (3, 5, 1, 10)) t(worker_id, c, w, g)"
_T1 = "SELECT 0 AS platform_id, worker_id, c::BIGINT AS c, w::BIGINT AS w, g::BIGINT AS g FROM (VALUES (1, 1, 2, 2), (2, 20, 40, 2)) t(worker_id, c, w, g)"
_REGIONS = f"SELECT platform_id, worker_id, c, w, g FROM ({platforms.REGIONS_SQL})"


def _selection(name: str, make: Callable[[SparkSession, str], DataFrame], sql: str, steps: int) -> None:
    for rule in ("global", "local"):
        QUERIES[f"{rule}_{name}"] = lambda spark, sf, rule=rule: select.trace(select.fold(select.as_rows(make(spark, sf)), steps, rule))
        ORACLES[f"{rule}_{name}"] = select.selection_sql(sql, steps, rule == "local")


_selection("t2", lambda spark, sf: platforms.literal(spark, platforms.THREE), _T2, 40)
_selection("t1", lambda spark, sf: platforms.literal(spark, platforms.FAST_SLOW), _T1, 20)
_selection("regions", platforms.regions, _REGIONS, 60)
for _rule in ("global2", "global2_receding", "local2", "local2_receding"):
    QUERIES[f"lookahead_{_rule}_t2"] = lambda spark, sf, rule=_rule: select.trace(select.fold(select.as_rows(platforms.literal(spark, platforms.THREE)), 60, rule))


@query("asymptotic_t2")
def _(spark, sf):
    """Work per communication time after a long run, by rule, for two platforms of three workers."""
    rows = select.as_rows(platforms.orders(spark, sf, 2, 3))
    out = None
    for rule in ("global", "local", "global2", "global2_receding"):
        one = select.asymptotic_ratio(select.fold(rows, 2000, rule)).select(F.lit(rule).alias("rule"), "platform_id", F.round("ratio", 3).alias("ratio"))
        out = one if out is None else out.union(one)
    return out


_RATES = """WITH x AS (SELECT *, 2.0::DOUBLE * c / (g * w) AS load FROM ({pf}) WHERE g > 0),
y AS (SELECT *, sum(load) OVER (PARTITION BY platform_id ORDER BY 2.0::DOUBLE * c / g, worker_id ROWS UNBOUNDED PRECEDING) AS upto FROM x)"""


@query("rate_bound_t2", "SELECT 0 AS platform_id, round(25 / 18.0, 9)::DOUBLE AS rate, round(5 / 6.0, 9)::DOUBLE AS rate_whole, 3::BIGINT AS enrolled")
def _(spark, sf):
    out = select.rates(platforms.literal(spark, platforms.THREE))
    return out.withColumns({k: F.round(k, 9) for k in ("rate", "rate_whole")})


@query(
    "bandwidth_first_regions",
    _RATES.format(pf=_REGIONS) + """ SELECT platform_id, worker_id, round(load, 9) AS load, round(greatest(0.0, least(1.0, (1.0 - (upto - load)) / load)), 6)::DOUBLE AS share FROM y""",
)
def _(spark, sf):
    rows = select.bandwidth_first(platforms.regions(spark, sf))
    return rows.select("platform_id", "worker_id", F.round("load", 9).alias("load"), F.round("share", 6).alias("share"))


@query("buffer_demand_t1")
def _(spark, sf):
    return select.buffer_demand(platforms.orders(spark, sf, 16, 4))


@query("rate_bound_check", f"SELECT platform_id, 60::BIGINT AS steps, 0::BIGINT AS beyond FROM ({_REGIONS}) WHERE g > 0 GROUP BY 1")
def _(spark, sf):
    """Steps of each platform's selection, and how many beat the steady-state bound."""
    platform = platforms.regions(spark, sf)
    folded = select.fold(select.as_rows(platform), 60, "global")
    beyond = select.check_rate_bound(folded, platform).groupBy("platform_id").agg(F.count("*").alias("beyond"))
    steps = select.trace(folded).groupBy("platform_id").agg(F.count("*").alias("steps"))
    return steps.join(beyond, "platform_id", "left").select("platform_id", "steps", F.coalesce("beyond", F.lit(0).cast("bigint")).alias("beyond"))


@query("preallocate_regions")
def _(spark, sf):
    platform = platforms.regions(spark, sf)
    return select.preallocate(select.trace(select.fold(select.as_rows(platform), 400, "global")), platform, 20, 4, 60)


def _planned(spark: SparkSession, rule: str, charge_c: int | None = None) -> DataFrame:
    """Messages of the three-worker platform for (20, 20, 160), by a selection that runs until all columns are owned."""
    platform = platforms.literal(spark, platforms.THREE)
    trace = select.trace(select.fold(select.as_rows(platform), select.until_owned(20, 20, 160), rule, charge_c=charge_c))
    return execute.messages(trace, platform, 20, 20, 160)


@query("execute_x1min", product_sql(20, 20, 160))
def _(spark, sf):
    """The product in the order of the selection, on the columns that each worker owns."""
    return execute.execute(matrices.left(spark, sf, 20, 20), matrices.right(spark, sf, 20, 160), _planned(spark, "local"))


@query("execute_charged_x1min", product_sql(20, 20, 160))
def _(spark, sf):
    """As execute_x1min, by the global rule with C charged."""
    return execute.execute(matrices.left(spark, sf, 20, 20), matrices.right(spark, sf, 20, 160), _planned(spark, "global", 20))


@query("execute_messages", execute.messages_sql(select.selection_sql(_T2, 2374, True), _T2, 20, 20, 160))
def _(spark, sf):
    """Tiles of A, B and C that the execution sends to each worker, and its first and last message."""
    return _planned(spark, "local").groupBy("worker_id").agg(F.count("*").alias("messages"), F.sum("a").alias("a"), F.sum("b").alias("b"), F.sum("c").alias("c"), F.min("step").alias("first"), F.max("step").alias("last"))


for _name, _workers, _sql in (("t1", platforms.FAST_SLOW, _T1), ("t2", platforms.THREE, _T2)):
    for _rule in ("global", "local"):
        QUERIES[f"{_rule}_charged_{_name}"] = lambda spark, sf, w=_workers, rule=_rule: select.trace(select.fold(select.as_rows(platforms.literal(spark, w)), 60, rule, charge_c=20))
        ORACLES[f"{_rule}_charged_{_name}"] = select.selection_sql(_sql, 60, _rule == "local", 20)


# ---- one-pass problem ------------------------------------------------------------------------------------------------------------------

_TOY = [("min_min", 2, 4, 7, 3, 3), ("min_min", 2, 8, 9, 6, 3), ("thrifty", 2, 4, 7, 3, 3), ("thrifty", 2, 8, 9, 6, 3), ("duplicate_b", 2, 4, 7, 3, 3), ("duplicate_b", 2, 8, 9, 6, 3)]
_ONE = "scenario_id int, policy string, p int, c int, w int, r int, s int"


@query("onepass_toy")
def _(spark, sf):
    return onepass.run(spark.createDataFrame([(n, *x) for n, x in enumerate(_TOY)], _ONE))


#: Link and task times of one worker, files of either kind.
ONE_WORKER = {"c": "1 + l_orderkey % 4", "w": "1 + l_partkey % 7", "r": "1 + l_suppkey % 4", "s": "1 + (l_orderkey + l_partkey) % 4"}


@query("alternating_optimal_check", f"SELECT count(*)::BIGINT AS lines, 0::BIGINT AS worse FROM lineitem WHERE {_KEYED}")
def _(spark, sf):
    """Lines, and those whose case some order serves sooner than alternation at one worker: expected none."""
    own = _drawn(spark, sf, ONE_WORKER).withColumn("scenario_id", F.expr("cast(((c * 10 + w) * 10 + r) * 10 + s as int)"))
    small = (F.col(k).cast("int").alias(k) for k in "cwrs")
    best = onepass.run(own.select("scenario_id", F.lit("exhaustive").alias("policy"), F.lit(1).alias("p"), *small)).select("scenario_id", F.col("makespan").alias("best"))
    both = onepass.alternating_makespan(own).join(best, "scenario_id")
    return both.agg(F.sum("lines").alias("lines"), F.sum(F.when(F.col("makespan") > F.col("best"), F.col("lines")).otherwise(0)).alias("worse"))


@query("alternating_grid")
def _(spark, sf):
    return onepass.alternating_makespan(_drawn(spark, sf, ONE_WORKER))


_TASKS = {"i": "l_suppkey % 100", "j": "l_partkey % 100"}


@query("dependence_edges", f"WITH x AS ({drawn_sql(_TASKS)}) SELECT 'A' || i AS file, i, j FROM x UNION ALL SELECT 'B' || j, i, j FROM x")
def _(spark, sf):
    """Tasks: the groups of suppliers and parts that meet in a line."""
    return onepass.dependence_edges(_drawn(spark, sf, _TASKS))


@query("reachable_tasks", "SELECT x, coalesce((SELECT max(y * (x - y)) FROM range(0, 7) t(y) WHERE y <= least(6, x) AND x - y <= 4), 0)::BIGINT AS tasks FROM (SELECT unnest(range(0, 11)) AS x)")
def _(spark, sf):
    return spark.createDataFrame([(x, onepass.reachable_tasks(x, 6, 4)) for x in range(11)], "x bigint, tasks bigint")


@query("onepass_winners", "SELECT * FROM (VALUES (4::BIGINT, 7::BIGINT, 'min_min', 49::BIGINT), (8, 9, 'thrifty', 132)) t(c, w, winner, makespan)")
def _(spark, sf):
    """Which greedy wins each counter-example, and its makespan."""
    runs = onepass.run(spark.createDataFrame([(n, *x) for n, x in enumerate(x for x in _TOY if x[0] != "duplicate_b")], _ONE))
    best = runs.groupBy(F.col("c").cast("bigint").alias("c"), F.col("w").cast("bigint").alias("w")).agg(F.min(F.struct("makespan", "policy")).alias("best"))
    return best.select("c", "w", F.col("best.policy").alias("winner"), "best.makespan")


# ---- schedulers ------------------------------------------------------------------------------------------------------------------------


@query("sched_set1")
def _(spark, sf):
    return schedulers.simulate(schedulers.scenarios(spark, schedulers.SET_ONE))


@query("sched_memory")
def _(spark, sf):
    return schedulers.simulate(schedulers.scenarios(spark, schedulers.SET_MEMORY))


@query("sched_q")
def _(spark, sf):
    """The same matrices and bytes with tiles of half the side: twice the tiles each way, four times the buffers, cheaper messages and updates."""
    coarse = schedulers.scenarios(spark, ((100, 100, 800, 10485),), c=400, w=56)
    fine = schedulers.scenarios(spark, ((200, 200, 1600, 41940),), c=100, w=7).withColumn("scenario_id", F.lit(1))
    return schedulers.simulate(coarse.unionByName(fine))


@query("sched_two_port")
def _(spark, sf):
    return schedulers.simulate(schedulers.scenarios(spark, schedulers.SET_ONE, port="two_port"))


@query("sched_regions")
def _(spark, sf):
    return schedulers.simulate(schedulers.on_platforms(platforms.regions(spark, sf), 40, 20, 80))


_RULES = " UNION ALL ".join(f"SELECT '{x}' AS rule, 0::BIGINT AS n" for x in schedulers.RULES)


@query("sched_invariants", _RULES)
def _(spark, sf):
    """Violations in whole traces of all policies: a ragged toy, and the shapes of all sets at a fifth of their side, with buffers for the same number of chunks."""
    shapes = tuple((r // 5, t // 5, s // 5, (schedulers.side("overlap", m) // 5 + 2) ** 2 - 4) for r, t, s, m in schedulers.SET_ONE + schedulers.SET_MEMORY)
    return schedulers.violations(schedulers.scenarios(spark, ((30, 20, 47, 140), *shapes)))


@query("sched_invariants_regions", _RULES)
def _(spark, sf):
    return schedulers.violations(schedulers.on_platforms(platforms.regions(spark, sf), 40, 20, 80))


@query("sched_similar")
def _(spark, sf):
    """Relative gap of each policy to the best of its scenario, and whether it counts as similar (within 6 %)."""
    runs = schedulers.simulate(schedulers.scenarios(spark, schedulers.SET_ONE))
    best = F.min("makespan").over(Window.partitionBy("scenario_id"))
    gap = F.col("makespan") / best - 1
    return runs.select("scenario_id", "policy", F.round(gap, 6).alias("gap"), (gap <= 0.06).alias("similar"))


@query(
    "sched_ranking",
    """SELECT s::INTEGER AS scenario_id, policy, "similar" FROM range(0, 3) t(s),
(VALUES ('rr_selected', true), ('rr_all', true), ('demand_overlap', true), ('demand_plain', true), ('minmin_overlap', false), ('third_demand', false)) p(policy, "similar")""",
)
def _(spark, sf):
    """Set one, as the experiments rank it: which policies come within 6 % of the best."""
    runs = QUERIES["sched_similar"](spark, sf).filter("policy <> 'fifth_demand'")  # of which nothing is reported
    return runs.select("scenario_id", "policy", "similar")


@query(
    "sched_workers",
    """SELECT s::INTEGER AS scenario_id, policy, n::INTEGER AS workers_used FROM range(0, 3) t(s), (VALUES ('rr_selected', 4), ('rr_all', 8), ('minmin_overlap', 2), ('demand_overlap', 8), ('demand_plain', 8), ('third_demand', 8), ('fifth_demand', 8)) p(policy, n)
UNION ALL SELECT * FROM (VALUES (3, 'rr_selected', 2), (4, 'rr_selected', 4)) v""",
)
def _(spark, sf):
    """Workers used in set one, and by the selecting policy with the least and the most memory of set three, as the experiments report them."""
    rows = schedulers.scenarios(spark, schedulers.SET_ONE)
    ends = schedulers.scenarios(spark, (schedulers.SET_MEMORY[0], schedulers.SET_MEMORY[-1]), ("rr_selected",)).withColumn("scenario_id", F.col("scenario_id") + 3)
    return schedulers.simulate(rows.unionByName(ends)).select("scenario_id", "policy", "workers_used")


# ---- LU --------------------------------------------------------------------------------------------------------------------------------

_LU_CASES = "(SELECT g * n AS r, g FROM (SELECT unnest([2, 4, 6])::BIGINT AS g), (SELECT unnest([1, 2, 3, 5, 10])::BIGINT AS n))"


@query("lu_costs", f"""WITH x AS {_LU_CASES}, y AS (SELECT r, g, r // g AS n, k, r - k * g AS q FROM x, range(1, 11) t(k) WHERE k <= r // g)
SELECT r, g, sum(2 * g * g + 4 * g * q + (n - k) * (g * g + 3 * g * q))::BIGINT AS messages, sum(g * g * g + g * g * q + (n - k) * q * g * g)::BIGINT AS updates, sum((n - k) * q * g * g)::BIGINT AS core_updates,
(r * r * r // g + r * r)::BIGINT AS messages_closed, ((r * r * r + 2 * g * g * r) // 3)::BIGINT AS updates_closed, ((2 * r * r * r - 3 * g * r * r + g * g * r) // 6)::BIGINT AS core_closed FROM y GROUP BY r, g""")
def _(spark, sf):
    return lu.totals(spark.createDataFrame([(g * n, g) for g in (2, 4, 6) for n in (1, 2, 3, 5, 10)], "r bigint, g bigint"))


@query("lu_chunk_shape", """SELECT g, gi, greatest(gi * gi // g, 1)::BIGINT AS width, round(gi / 3.0, 9)::DOUBLE AS square, round(gi * gi / (g + 2.0::DOUBLE * gi * gi / g), 9) AS columns, CASE WHEN 2 * gi <= g THEN 'square' ELSE 'columns' END AS shape
FROM (SELECT unnest([8, 12, 20])::BIGINT AS g), range(1, 20) t(gi) WHERE gi < g""")
def _(spark, sf):
    return lu.chunk_shape(spark.createDataFrame([(g, gi) for g in (8, 12, 20) for gi in range(1, g)], "g bigint, gi bigint"))


@query("lu_virtual_workers", f"SELECT worker_id, 4::BIGINT AS g, g AS gi, unnest(range(1, g * g // 16 + 1)) AS part FROM ({_REGIONS}) WHERE g >= 4")
def _(spark, sf):
    own = platforms.regions(spark, sf).filter("g >= 4").select("worker_id", F.lit(4).cast("bigint").alias("g"), F.col("g").alias("gi"))
    return lu.virtual_workers(own)


@query("lu_enrol", "SELECT g, (SELECT min(p) FROM range(1, 1000) t(p) WHERE 3 * 100 * p >= g * 7)::BIGINT AS p FROM (SELECT unnest([10, 50, 100, 300])::BIGINT AS g)")
def _(spark, sf):
    rows = spark.createDataFrame([(g,) for g in (10, 50, 100, 300)], "g bigint")
    return rows.select("g", lu.enrolled(F.col("g"), F.lit(100), F.lit(7)).alias("p"))


@query("lu_plan_regions")
def _(spark, sf):
    return lu.plan(platforms.regions(spark, sf), 60)


def _whole(spark: SparkSession, m: DataFrame, n: int, q: int) -> DataFrame:
    """Tiles of m (row, col, val); rows without a cell, and those beyond the edge, get a pivot of one."""
    own = m.select("row").distinct()
    pad = spark.range(-(-n // q) * q).join(own, F.col("id") == F.col("row"), "left_anti").select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(1.0).alias("val"))
    return tiles.to_tiles(m.select("row", "col", F.col("val").cast("double").alias("val")).unionByName(pad), q)


def _reconstructed(spark: SparkSession, m: DataFrame, n: int, q: int, g: int = 1) -> DataFrame:
    """Product of the factors of m (row, col, val), rounded: must be m again."""
    blocks, own = -(-n // q), m.select("row").distinct()
    low, up = lu.factor(_whole(spark, m, n, q), blocks, q, Scratch(spark, "lu"), g)
    back = tiles.to_cells(tiles.resident_multiply(low, up, blocks, blocks, max(1, -(-blocks // 3)), q), q)
    return back.join(F.broadcast(own), "row", "left_semi").filter(F.col("col") < n).select("row", "col", F.round("val").cast("bigint").alias("val")).filter("val <> 0")


def _trade_matrix(spark: SparkSession, sf: str) -> DataFrame:
    return matrices.trade(spark, sf).select(F.col("i").cast("bigint").alias("row"), F.col("j").cast("bigint").alias("col"), F.col("v").alias("val"))


@query("lu_trade_reconstruct", f"SELECT i::BIGINT AS row, j::BIGINT AS col, v AS val FROM ({matrices.TRADE_SQL}) WHERE v <> 0")
def _(spark, sf):
    return _reconstructed(spark, _trade_matrix(spark, sf), 25, 5)


@query("lu_blocked_reconstruct", f"SELECT i::BIGINT AS row, j::BIGINT AS col, v AS val FROM ({matrices.TRADE_SQL}) WHERE v <> 0")
def _(spark, sf):
    """Second-level blocks of two tiles, of which the last is ragged."""
    return _reconstructed(spark, _trade_matrix(spark, sf), 25, 5, 2)


@query("lu_trade_residual", "SELECT 0.0::DOUBLE AS largest, 0.0::DOUBLE AS relative")
def _(spark, sf):
    """Greatest entry and relative norm of M - L U, to nine digits."""
    m = _trade_matrix(spark, sf)
    low, up = lu.factor(_whole(spark, m, 25, 5), 5, 5, Scratch(spark, "lu"))
    return lu.residual(m, low, up, 5, 5).select(F.abs(F.round("largest", 6)).alias("largest"), F.abs(F.round("relative", 9)).alias("relative"))


@query("norms_x1a", f"""WITH a AS ({matrices.a_sql(100, 100)}) SELECT max(abs(v)) AS largest, (SELECT max(s) FROM (SELECT sum(abs(v)) AS s FROM a GROUP BY k))::BIGINT AS one,
(SELECT max(s) FROM (SELECT sum(abs(v)) AS s FROM a GROUP BY i))::BIGINT AS inf, sum(v * v)::BIGINT AS square FROM a""")
def _(spark, sf):
    return tiles.norms(matrices.left(spark, sf, 100, 100).toDF("row", "col", "val"))


@query("block_x1a", f"SELECT i - 20 AS row, k - 40 AS col, v AS val FROM ({matrices.a_sql(100, 100)}) WHERE i >= 20 AND i < 60 AND k >= 40 AND k < 60")
def _(spark, sf):
    """A block of tiles of side 4, re-tiled to side 10."""
    whole = tiles.to_tiles(matrices.left(spark, sf, 100, 100).toDF("row", "col", "val"), 4)
    part = tiles.retile(tiles.block(whole, (5, 15), (10, 15)), 4, 10)
    return tiles.to_cells(part, 10).select("row", "col", F.round("val").cast("bigint").alias("val")).filter("val <> 0")


@query("lu_gram_reconstruct", f"WITH e AS ({matrices.EMBED_SQL}) SELECT * FROM (SELECT x.col AS row, y.col AS col, sum(x.val * y.val)::BIGINT AS val FROM e x JOIN e y ON x.row = y.row GROUP BY 1, 2) WHERE val <> 0")
def _(spark, sf):
    return _reconstructed(spark, QUERIES["gram_embeddings"](spark, sf), 64, 16, 2)


# ---- streaming -------------------------------------------------------------------------------------------------------------------------

_HOUR = "date_trunc('hour', ts)"
PANEL_SQL = f"""WITH a AS (SELECT {_HOUR} AS h, user_id % 8 AS i, count(*) AS a FROM events GROUP BY 1, 2), b AS (SELECT {_HOUR} AS h, event_type AS j, count(*) AS b FROM events GROUP BY 1, 2)
SELECT i, j, sum(a * b)::BIGINT AS c FROM a JOIN b USING (h) GROUP BY 1, 2"""


@query("panels_hourly", PANEL_SQL)
def _(spark, sf):
    return panels.product_of_panels(panels.finish(panels.outer_products(panels.stream(spark, sf)), "complete"))


@query("panels_batch", PANEL_SQL)
def _(spark, sf):
    return panels.product_of_panels(panels.outer_products(panels.batch(spark, sf)))


@query("late_panels", PANEL_SQL)
def _(spark, sf):
    return panels.late_panels(panels.batch(spark, sf), "2024-01-20 00:00:00")


@query("resident_state", "SELECT user_id % 8 AS i, count(*)::BIGINT AS n, sum(round(value * 100))::BIGINT AS total FROM events GROUP BY 1")
def _(spark, sf):
    return panels.finish(panels.resident_state(panels.replay(spark, sf)), "update", ("i",))


@query("sliding_counts", f"""SELECT strftime(h - to_hours(k), '%Y-%m-%d %H:%M') AS start, event_type, count(*)::BIGINT AS n FROM (SELECT {_HOUR} AS h, event_type FROM events), range(0, 2) t(k) GROUP BY 1, 2""")
def _(spark, sf):
    return panels.finish(panels.sliding(panels.stream(spark, sf)), "complete").select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


@query("session_counts", """WITH x AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
y AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM x)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*)::BIGINT AS n FROM y GROUP BY user_id, k""")
def _(spark, sf):
    return panels.sessions(panels.batch(spark, sf)).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("dedup_events", "SELECT event_type, count(DISTINCT event_id)::BIGINT AS n FROM events GROUP BY 1")
def _(spark, sf):
    return panels.finish(panels.distinct_events(panels.stream(spark, sf))).groupBy("event_type").agg(F.count("*").alias("n"))


@query("interval_join", """SELECT a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY
WHERE a.event_type = 'signup' AND b.event_type = 'purchase'""")
def _(spark, sf):
    return panels.finish(panels.interval_join(panels.stream(spark, sf)))


@query("demand_hourly", f"SELECT strftime({_HOUR}, '%Y-%m-%d %H') AS hour, count(*)::BIGINT AS n, ceil(count(*) / 4.0)::BIGINT AS workers FROM events GROUP BY 1")
def _(spark, sf):
    return panels.demand(panels.batch(spark, sf), 4).select(F.date_format("hour", "yyyy-MM-dd HH").alias("hour"), "n", "workers")


_CLOSED = f"(SELECT * FROM events WHERE {_HOUR} + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events))"


@query("panels_accumulated", PANEL_SQL.replace("FROM events", f"FROM {_CLOSED}"))
def _(spark, sf):
    """C merged micro-batch by micro-batch from the panels that the watermark closes."""
    return panels.accumulated(panels.replay(spark, sf))


@query("resident_tiles_stream", PANEL_SQL)
def _(spark, sf):
    """C as tiles in the state of its chunks, three micro-batches."""
    return panels.finish(panels.resident_tiles(panels.replay(spark, sf)), "update", ("i", "j"))


#: Rows that come in the file of their quarter of the time, or two files late, and not after the watermark that the micro-batch before began with has closed their hour.
_IN_TIME = f"""WITH e AS (SELECT *, {_HOUR} AS h, epoch_us(ts) AS us FROM events), b AS (SELECT min(us) AS lo, max(us) AS hi FROM e),
f AS (SELECT e.*, least(3, (us - lo) * 4 // (hi - lo + 1) + CASE WHEN event_id % 50 = 0 THEN 2 ELSE 0 END) AS file FROM e, b),
w AS (SELECT x.file, max(y.ts) - INTERVAL 1 HOUR AS closed FROM (SELECT DISTINCT file FROM f) x LEFT JOIN f y ON y.file < x.file - 1 GROUP BY x.file),
k AS (SELECT f.* FROM f JOIN w ON f.file = w.file WHERE closed IS NULL OR h + INTERVAL 1 HOUR > closed)"""


@query("late_stream", f"{_IN_TIME} SELECT strftime(h, '%Y-%m-%d %H') AS hour, user_id % 8 AS i, event_type, count(*)::BIGINT AS n FROM k GROUP BY 1, 2, 3")
def _(spark, sf):
    """Hourly panels of a stream in which every fiftieth event comes two files late: those whose hour the watermark has closed are dropped, the others are counted."""
    rows = panels.finish(panels.outer_products(panels.replay(spark, sf, 4, late_every=50)), "update", ("hour", "i", "event_type"))
    return rows.withColumn("hour", F.date_format("hour", "yyyy-MM-dd HH"))


@query(
    "backlog_stream",
    """WITH RECURSIVE e AS (SELECT user_id % 4 AS pool, epoch_ms(ts) // 3600000 AS h FROM events), n AS (SELECT pool, h, count(*) AS n FROM e GROUP BY 1, 2),
a AS (SELECT pool, min(h) AS lo, max(h) AS hi FROM n GROUP BY 1), s AS (SELECT a.pool, x.h, coalesce(n.n, 0) AS n, a.lo FROM a, LATERAL (SELECT unnest(range(lo, hi + 1)) AS h) x LEFT JOIN n ON n.pool = a.pool AND n.h = x.h),
r AS (SELECT pool, lo - 1 AS h, 0::BIGINT AS n, 0::BIGINT AS workers, 0::BIGINT AS waiting FROM a
  UNION ALL SELECT s.pool, s.h, s.n, least(2, (r.waiting + s.n + 1) // 2)::BIGINT, (r.waiting + s.n - least(r.waiting + s.n, 2 * least(2, (r.waiting + s.n + 1) // 2)))::BIGINT FROM r JOIN s ON s.pool = r.pool AND s.h = r.h + 1)
SELECT r.pool, (r.h * 3600000)::BIGINT AS hour, r.n, workers, waiting FROM r JOIN a ON a.pool = r.pool WHERE r.h >= lo""",
)
def _(spark, sf):
    """Demand-driven enrolment with what waits as state: two workers a pool at most, two events an hour each."""
    return panels.finish(panels.backlog(panels.replay(spark, sf, utc=True), 2, 2), "update", ("pool", "hour"))


# ---- relational surround ---------------------------------------------------------------------------------------------------------------


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("bigint")


@query("asof_last_signup", """SELECT e.event_id, coalesce((SELECT max(s.event_id) FROM events s WHERE s.event_type = 'signup' AND s.user_id = e.user_id AND s.ts = (SELECT max(x.ts) FROM events x WHERE x.event_type = 'signup' AND x.user_id = e.user_id AND x.ts <= e.ts)), -1)::BIGINT AS signup_id
FROM events e WHERE e.event_type = 'purchase'""")
def _(spark, sf):
    """As-of join by a window: the last signup of a user up to each purchase."""
    rows = table(spark, sf, "events").filter(F.col("event_type").isin("signup", "purchase"))
    sign = F.when(F.col("event_type") == "signup", F.col("event_id"))
    last = F.last(sign, ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase", "event_id"))
    return rows.select("event_id", "event_type", F.coalesce(last, F.lit(-1)).alias("signup_id")).filter("event_type = 'purchase'").drop("event_type")


@query("range_join_price_bands", """WITH b AS (SELECT n AS band, n * 200 AS low, (n + 1) * 200 AS high FROM range(0, 20) t(n)) SELECT band, count(*)::BIGINT AS parts FROM part JOIN b ON p_retailprice >= low AND p_retailprice < high GROUP BY 1""")
def _(spark, sf):
    bands = spark.range(20).select(F.col("id").alias("band"), (F.col("id") * 200).alias("low"), ((F.col("id") + 1) * 200).alias("high"))
    part = table(spark, sf, "part").select("p_retailprice")
    return part.join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("low")) & (F.col("p_retailprice") < F.col("high"))).groupBy("band").agg(F.count("*").alias("parts"))


@query("anti_suppliers", "SELECT s_suppkey FROM supplier WHERE s_suppkey NOT IN (SELECT l_suppkey FROM lineitem WHERE l_quantity > 49 AND l_discount >= 0.09 AND l_tax >= 0.07)")
def _(spark, sf):
    return table(spark, sf, "supplier").join(table(spark, sf, "lineitem").filter("l_quantity > 49 AND l_discount >= 0.09D AND l_tax >= 0.07D"), F.col("s_suppkey") == F.col("l_suppkey"), "left_anti").select("s_suppkey")


@query("semi_parts", "SELECT p_partkey, p_brand FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50)")
def _(spark, sf):
    return table(spark, sf, "part").join(table(spark, sf, "lineitem").filter("l_quantity >= 50"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey", "p_brand")


def _trade(spark: SparkSession, sf: str) -> DataFrame:
    o, c, n = (table(spark, sf, x) for x in ("orders", "customer", "nation"))
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).select("n_regionkey", "c_mktsegment", cents("o_totalprice").alias("cents"))


_LEVELS = ("coalesce(n_regionkey, -1) AS region", "coalesce(c_mktsegment, 'all') AS segment")
_TRADE = "SELECT n_regionkey, c_mktsegment, round(o_totalprice * 100)::BIGINT AS cents FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"


@query("cube_trade", f"SELECT coalesce(n_regionkey, -1) AS region, coalesce(c_mktsegment, 'all') AS segment, sum(cents)::BIGINT AS cents, count(*)::BIGINT AS n FROM ({_TRADE}) GROUP BY CUBE (n_regionkey, c_mktsegment)")
def _(spark, sf):
    return _trade(spark, sf).cube("n_regionkey", "c_mktsegment").agg(F.sum("cents").alias("cents"), F.count("*").alias("n")).selectExpr(*_LEVELS, "cents", "n")


@query("grouping_sets_trade", f"SELECT coalesce(n_regionkey, -1) AS region, coalesce(c_mktsegment, 'all') AS segment, count(*)::BIGINT AS n FROM ({_TRADE}) GROUP BY GROUPING SETS ((n_regionkey), (c_mktsegment), ())")
def _(spark, sf):
    return _trade(spark, sf).groupingSets([["n_regionkey"], ["c_mktsegment"], []], "n_regionkey", "c_mktsegment").agg(F.count("*").alias("n")).selectExpr(*_LEVELS, "n")


@query("pivot_segment", f"""SELECT n_regionkey, count(*) FILTER (c_mktsegment = 'BUILDING')::BIGINT AS building, count(*) FILTER (c_mktsegment = 'HOUSEHOLD')::BIGINT AS household FROM ({_TRADE}) GROUP BY 1""")
def _(spark, sf):
    wide = _trade(spark, sf).groupBy("n_regionkey").pivot("c_mktsegment", ["BUILDING", "HOUSEHOLD"]).count()
    return wide.select("n_regionkey", *(F.coalesce(F.col(c), F.lit(0)).cast("bigint").alias(c.lower()) for c in ("BUILDING", "HOUSEHOLD")))


@query("topk_cells", f"SELECT i, j, c FROM ({product_sql(100, 100, 800)}) ORDER BY c DESC, i, j LIMIT 20")
def _(spark, sf):
    return QUERIES["resident_sql_x1a"](spark, sf).orderBy(F.desc("c"), "i", "j").limit(20)


@query("window_ranks", """SELECT s_suppkey, rank() OVER w AS rk, dense_rank() OVER w AS dense, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY bal, s_suppkey) AS quarter, coalesce(bal - lag(bal) OVER (PARTITION BY s_nationkey ORDER BY bal, s_suppkey), 0)::BIGINT AS step
FROM (SELECT *, round(s_acctbal * 100)::BIGINT AS bal FROM supplier) WINDOW w AS (PARTITION BY s_nationkey ORDER BY bal)""")
def _(spark, sf):
    rows = table(spark, sf, "supplier").withColumn("bal", cents("s_acctbal"))
    w, v = Window.partitionBy("s_nationkey").orderBy("bal"), Window.partitionBy("s_nationkey").orderBy("bal", "s_suppkey")
    long_ = lambda c: c.cast("bigint")
    return rows.select("s_suppkey", long_(F.rank().over(w)).alias("rk"), long_(F.dense_rank().over(w)).alias("dense"), long_(F.ntile(4).over(v)).alias("quarter"), F.coalesce(F.col("bal") - F.lag("bal").over(v), F.lit(0)).alias("step"))


@query("json_props", "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS total FROM events GROUP BY 1")
def _(spark, sf):
    return table(spark, sf, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("bigint")).alias("total"))


@query("array_scalars", """SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::BIGINT AS positive, floor(list_max(embedding)::DOUBLE * 1000 + 0.5)::BIGINT AS top FROM embeddings""")
def _(spark, sf):
    e = F.col("embedding")
    return table(spark, sf, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("bigint").alias("positive"), F.floor(F.array_max(e).cast("double") * 1000 + 0.5).cast("bigint").alias("top"))


@query("string_scalars", "SELECT p_partkey, upper(p_name) AS name, split_part(p_brand, '#', 2) AS brand, length(p_type)::BIGINT AS n FROM part")
def _(spark, sf):
    return table(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("name"), F.split_part("p_brand", F.lit("#"), F.lit(2)).alias("brand"), F.length("p_type").cast("bigint").alias("n"))


@query("date_scalars", "SELECT year(o_orderdate)::BIGINT AS y, month(o_orderdate)::BIGINT AS m, count(*)::BIGINT AS n, sum(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::BIGINT AS days FROM orders GROUP BY 1, 2")
def _(spark, sf):
    d = F.col("o_orderdate")
    days = F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date"))
    return table(spark, sf, "orders").groupBy(F.year(d).cast("bigint").alias("y"), F.month(d).cast("bigint").alias("m")).agg(F.count("*").alias("n"), F.sum(days).cast("bigint").alias("days"))


@query("approx_distinct")
def _(spark, sf):
    return table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The smallest product of the experiments by the resident-result kernel."""
    a, b = matrices.left(spark, sf, 20, 20), matrices.right(spark, sf, 20, 160)
    return multiply.chunked(a, b, multiply.Cut.squares(20, 160, 4))


QUERIES["resident_sql_min"] = flagship
ORACLES["resident_sql_min"] = product_sql(20, 20, 160)
