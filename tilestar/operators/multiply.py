"""Products C + A*B of matrices in coordinate form, as dataflows whose shuffled rows are the tiles that the methods move.

A is (i, k, v), B is (k, j, u), C is (i, j, c); missing coordinates are zero, repeated ones are summed. All give (i, j, c) with the
coordinates that have a product or a C. One coordinate stands for one tile, so the block shapes of the experiments are kept.

Most methods differ only in how the result is cut into chunks: rows of A go to every chunk column, rows of B to every chunk row, and meet
there. `Cut` is that choice. A cut's tables are bounded by the number of chunks along one side and travel as expressions or broadcasts.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import isqrt

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from tilestar.runtime import BROADCAST_MEMORY, Scratch, in_memory

#: Bytes of a coordinate row in memory with its place in a hashed relation, for the size check of broadcasts.
ROW_BYTES = 64


def _side(x: Column, edges: list[int]) -> Column:
    """Index of the part that x lies in; edges: first coordinates of the parts, ascending from 0."""
    return F.aggregate(F.array(*(F.lit(e).cast("bigint") for e in edges)), F.lit(-1), lambda n, e: n + F.when(x >= e, 1).otherwise(0))


@dataclass(frozen=True)
class Cut:
    """Where the rows and the columns of the result are cut."""

    rows: tuple[int, ...]
    cols: tuple[int, ...]
    #: parts are of this size if above 0, which spares the look-up
    row_step: int = 0
    col_step: int = 0

    @staticmethod
    def squares(r: int, s: int, g: int, h: int | None = None) -> Cut:
        h = h or g
        return Cut(tuple(range(0, r, g)), tuple(range(0, s, h)), g, h)

    def row(self, i: Column) -> Column:
        return F.floor(i / self.row_step).cast("int") if self.row_step else _side(i, list(self.rows))

    def col(self, j: Column) -> Column:
        return F.floor(j / self.col_step).cast("int") if self.col_step else _side(j, list(self.cols))


def _all(n: int, name: str) -> Column:
    return F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias(name)


def _useful(a: DataFrame, b: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Columns of A without a row of B, and the reverse, are dropped before they are replicated."""
    return a.join(b.select("k").distinct(), "k", "left_semi"), b.join(a.select("k").distinct(), "k", "left_semi")


def replicate(a: DataFrame, b: DataFrame, cut: Cut) -> tuple[DataFrame, DataFrame]:
    """A to every chunk column and B to every chunk row: the messages of the method."""
    left = a.select(cut.row(F.col("i")).alias("ci"), _all(len(cut.cols), "cj"), "k", "i", "v")
    right = b.select(_all(len(cut.rows), "ci"), cut.col(F.col("j")).alias("cj"), "k", "j", "u")
    return left, right


def _add(product: DataFrame, c: DataFrame | None) -> DataFrame:
    """product (i, j, c) with the old C as further addends."""
    if c is None:
        return product
    return product.unionByName(c.select("i", "j", "c")).groupBy("i", "j").agg(F.sum("c").alias("c"))


def _tagged(left: DataFrame, right: DataFrame, old: DataFrame | None, n_rows: int | None) -> DataFrame:
    """Messages as (part, ci, cj, k, kind, at, x): at is the row or column of the result; an old C of column j goes as an A of the inner index -1 - j.

    left: (ci, cj, k, i, v), right: (ci, cj, k, j, u), old: (ci, cj, i, j, c); n_rows: chunks along a column of chunks. Chunks are dealt to tasks in turn; without n_rows
    ci is a worker, and all its chunks are its own.
    """
    tasks = int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    part = F.pmod(F.col("ci") if n_rows is None else F.col("cj") * n_rows + F.col("ci"), F.lit(tasks)).cast("int").alias("part")
    whole = lambda name: F.col(name).cast("bigint")
    row = lambda df, kind, k, at, x: df.select(part, "ci", "cj", k.alias("k"), F.lit(kind).alias("kind"), at.alias("at"), F.col(x).alias("x"))
    sent = row(left, "A", whole("k"), whole("i"), "v").unionByName(row(right, "B", whole("k"), whole("j"), "u"))
    return sent if old is None else sent.unionByName(row(old, "C", -1 - whole("j"), whole("i"), "c"))


def _sent(a: DataFrame, b: DataFrame, cut: Cut, c: DataFrame | None) -> DataFrame:
    """All messages of a cut."""
    old = None if c is None else c.select(cut.row(F.col("i")).alias("ci"), cut.col(F.col("j")).alias("cj"), "i", "j", "c")
    return _tagged(*replicate(a, b, cut), old, len(cut.rows))


def _resident(sent: DataFrame, depth: int = 1) -> DataFrame:
    """One exchange, by chunk; then each chunk meets its panels and sums in place, in the task that holds it.

    A panel is what one inner index needs: at most a chunk's height of A and its width of B. With depth > 1 so many inner indices are gathered first, as squares of A and B.
    """
    tasks = int(sent.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    chunk = ["part", "ci", "cj"]
    of = lambda on: F.collect_list(F.when(on, F.struct("at", "x")))
    held = sent.repartitionById(tasks, F.col("part")).groupBy(*chunk, "k").agg(of(F.col("kind") != "B").alias("column"), of(F.col("kind") == "B").alias("row"))
    own = F.array(F.struct((-1 - F.col("k")).alias("at"), F.lit(1).cast(sent.schema["x"].dataType).alias("x")))
    held = held.withColumn("row", F.when(F.col("k") < 0, own).otherwise(F.col("row"))).filter((F.size("column") > 0) & (F.size("row") > 0))
    if depth > 1:
        held = held.groupBy(*chunk, F.floor(F.col("k") / depth).alias("square")).agg(F.collect_list(F.struct("column", "row")).alias("panels"))
        held = held.select(*chunk, F.explode("panels").alias("p")).select(*chunk, "p.column", "p.row")
    met = held.select(*chunk, F.explode("column").alias("a"), "row").select(*chunk, "a", F.explode("row").alias("b"))
    done = met.groupBy(*chunk, F.col("a.at").alias("i"), F.col("b.at").alias("j")).agg(F.sum(F.col("a.x") * F.col("b.x")).alias("c"))
    return done.select("i", "j", "c")


def owned(left: DataFrame, right: DataFrame, old: DataFrame | None = None) -> DataFrame:
    """Product of messages (worker ci, chunk cj): each worker's chunks stay in its task."""
    return _resident(_tagged(left, right, old, None))


def chunked(a: DataFrame, b: DataFrame, cut: Cut, c: DataFrame | None = None, prune: bool = False, depth: int = 1) -> DataFrame:
    """Resident-result product: each chunk gathers its C, A and B rows by one exchange, and sums in place. More chunks than tasks keep all tasks busy."""
    if prune:
        a, b = _useful(a, b)
    return _resident(_sent(a, b, cut, c), depth)


def split(a: DataFrame, b: DataFrame, r: int, s: int, m: int, parts: int, c: DataFrame | None = None) -> DataFrame:
    """Memory of m tiles split in 3 or 5 equal squares: one holds C, the others A and B squares that are as deep as they are wide (with five, two are on their way)."""
    g = max(1, isqrt(m // parts))
    return chunked(a, b, Cut.squares(r, s, g), c, depth=g)


def messages(a: DataFrame, b: DataFrame, r: int, s: int, cut: Cut) -> DataFrame:
    """(kind, tiles) that `chunked` moves with a dense C: rows counted where they enter the exchange, and where they leave the product, as it runs."""
    spark = a.sparkSession
    zero = spark.range(r * s).select(F.floor(F.col("id") / s).alias("i"), (F.col("id") % s).alias("j"), F.lit(0).cast(a.schema["v"].dataType).alias("c"))
    entered, left = Observation(), Observation()
    count = lambda kind: F.sum(F.when(F.col("kind") == kind, 1).otherwise(0)).alias(kind)
    sent = _sent(a, b, cut, zero).observe(entered, count("A"), count("B"), count("C"))
    _resident(sent).observe(left, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    rows = [("A", entered.get["A"]), ("B", entered.get["B"]), ("C_in", entered.get["C"]), ("C_out", left.get["n"])]
    return spark.createDataFrame([(k, int(n or 0)) for k, n in rows], "kind string, tiles bigint")


def inner_join(a: DataFrame, b: DataFrame, c: DataFrame | None = None, salt: int = 1) -> DataFrame:
    """Join on the inner index, then sum; salt > 1 splits a hot inner index by rows of A."""
    if salt > 1:
        a = a.withColumn("z", F.pmod(F.xxhash64("i"), F.lit(salt)).cast("int"))
        b = b.withColumn("z", _all(salt, "z"))
        met = a.join(b, ["k", "z"])
    else:
        met = a.join(b, "k")
    return _add(met.groupBy("i", "j").agg(F.sum(F.col("v") * F.col("u")).alias("c")), c)


def inner_join_heavy(a: DataFrame, b: DataFrame, heavy: int = 100_000, salt: int = 16) -> DataFrame:
    """As `inner_join`; an inner index that more than `heavy` rows of A have is split by rows of A, and its rows of B go to every part. Others are joined as they are."""
    hot = a.groupBy("k").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > heavy).select("k", F.lit(True).alias("hot"))
    hot = Scratch(a.sparkSession, "heavy").save(hot, "hot")
    hot = F.broadcast(hot) if in_memory(hot) <= BROADCAST_MEMORY else hot
    left = a.join(hot, "k", "left").withColumn("z", F.when(F.col("hot"), F.pmod(F.xxhash64("i"), F.lit(salt)).cast("int")).otherwise(0))
    every = F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(salt - 1))).otherwise(F.array(F.lit(0)))
    right = b.join(hot, "k", "left").withColumn("z", F.explode(every))
    return left.select("k", "z", "i", "v").join(right.select("k", "z", "j", "u"), ["k", "z"]).groupBy("i", "j").agg(F.sum(F.col("v") * F.col("u")).alias("c"))


def broadcast(a: DataFrame, b: DataFrame, c: DataFrame | None = None, most: int = BROADCAST_MEMORY) -> DataFrame:
    """B everywhere, A partitioned: B, written once, is broadcast if its rows in memory fit the bound, and joined by a shuffle otherwise."""
    b = Scratch(b.sparkSession, "broadcast").save(b, "b")
    return inner_join(a, F.broadcast(b) if b.count() * ROW_BYTES <= most else b, c)


def shares(total: int, speeds: list[int]) -> list[int]:
    """First coordinates of parts of `total`, sized by speed; parts without a coordinate are left out."""
    whole, run, edges = sum(speeds), 0, []
    for v in speeds:
        edges.append(total * run // whole)
        run += v
    return sorted(set(edges))


def slabs(a: DataFrame, b: DataFrame, r: int, speeds: list[int], c: DataFrame | None = None) -> DataFrame:
    """Row slabs of heights by speed; B goes to every slab."""
    return chunked(a, b, Cut(tuple(shares(r, speeds)), (0,)), c)


def grid(a: DataFrame, b: DataFrame, r: int, s: int, p1: int, p2: int, c: DataFrame | None = None) -> DataFrame:
    """p1 x p2 super-blocks of the result, one outer product per inner index."""
    return chunked(a, b, Cut.squares(r, s, -(-r // p1), -(-s // p2)), c)


def weighted_grid(a: DataFrame, b: DataFrame, r: int, s: int, row_speeds: list[int], col_speeds: list[int], c: DataFrame | None = None) -> DataFrame:
    """A grid whose heights and widths follow sorted speeds; the best arrangement is NP-complete, sorting is the heuristic."""
    return chunked(a, b, Cut(tuple(shares(r, sorted(row_speeds, reverse=True))), tuple(shares(s, sorted(col_speeds, reverse=True)))), c)


def shifted(a: DataFrame, b: DataFrame, r: int, t: int, s: int, p: int, c: DataFrame | None = None) -> DataFrame:
    """Skew, then p rotation steps on a p x p grid: in step n, block (I, J) of the result receives and multiplies inner block (I + J + n) mod p. Blocks of the result stay where they are."""
    height, depth, width = -(-r // p), -(-t // p), -(-s // p)
    block = lambda x, size: F.floor(F.col(x) / size).cast("int")
    steps = F.explode(F.sequence(F.lit(0), F.lit(p - 1))).alias("n")
    left = a.select(block("i", height).alias("ci"), block("k", depth).alias("bk"), "i", "k", "v", steps)
    right = b.select(block("j", width).alias("cj"), block("k", depth).alias("bk"), "j", "k", "u", steps)
    left = left.withColumn("cj", F.pmod(F.col("bk") - F.col("ci") - F.col("n"), F.lit(p)))
    right = right.withColumn("ci", F.pmod(F.col("bk") - F.col("cj") - F.col("n"), F.lit(p)))
    old = None if c is None else c.select(block("i", height).alias("ci"), block("j", width).alias("cj"), "i", "j", "c")
    return _resident(_tagged(left, right, old, p))


def packed_rectangles(r: int, s: int, speeds: list[int]) -> list[tuple[int, int, int, int]]:
    """(i0, i1, j0, j1) for each worker, area by speed: workers sorted by speed, grouped in about sqrt(p) columns."""
    order = sorted(range(len(speeds)), key=lambda k: (-speeds[k], k))
    n_cols = max(1, round(len(speeds) ** 0.5))
    groups = [order[k::n_cols] for k in range(n_cols)]
    widths = [sum(speeds[k] for k in g) for g in groups]
    out, j_run = [], 0
    for g, width in zip(groups, widths, strict=True):
        j0, j1 = s * j_run // sum(widths), s * (j_run + width) // sum(widths)
        j_run, i_run = j_run + width, 0
        for k in g:
            out.append((r * i_run // width, r * (i_run + speeds[k]) // width, j0, j1))
            i_run += speeds[k]
    return out


def rectangles(a: DataFrame, b: DataFrame, r: int, s: int, speeds: list[int], c: DataFrame | None = None) -> DataFrame:
    """Irregular rectangles, one a worker."""
    own = a.sparkSession.createDataFrame([(n, *x) for n, x in enumerate(packed_rectangles(r, s, speeds))], "ci int, i0 bigint, i1 bigint, j0 bigint, j1 bigint")
    own = F.broadcast(own.withColumn("cj", F.lit(0)))  # one row a worker
    rows, cols = (F.col("i") >= F.col("i0")) & (F.col("i") < F.col("i1")), (F.col("j") >= F.col("j0")) & (F.col("j") < F.col("j1"))
    old = None if c is None else c.join(own, rows & cols).select("ci", "cj", "i", "j", "c")
    return _resident(_tagged(a.join(own, rows).select("ci", "cj", "k", "i", "v"), b.join(own, cols).select("ci", "cj", "k", "j", "u"), old, len(speeds)))


def inner_split(a: DataFrame, b: DataFrame, parts: int, c: DataFrame | None = None) -> DataFrame:
    """For a small result: the inner index is cut in parts, each makes a whole partial result, and they are summed in two levels."""
    cut = lambda df: df.withColumn("part", F.pmod(F.xxhash64("k"), F.lit(parts)).cast("int"))
    partial = cut(a).join(cut(b), ["part", "k"]).groupBy("part", "i", "j").agg(F.sum(F.col("v") * F.col("u")).alias("c"))
    return _add(partial.groupBy("i", "j").agg(F.sum("c").alias("c")), c)


def assign_columns(spark, r: int, s: int, g: int, p: int) -> DataFrame:
    """(ci, cj, worker): whole chunk columns dealt to p workers in turn."""
    rows = spark.range(-(-r // g) * -(-s // g)).withColumnRenamed("id", "n")
    ci, cj = F.col("n") % -(-r // g), F.floor(F.col("n") / -(-r // g)).cast("bigint")
    return rows.select(ci.alias("ci"), cj.alias("cj"), (cj % p + 1).alias("worker"))


def cost_table(r: int, t: int, s: int, nnz_a: int, nnz_b: int, m: int, workers: int = 8) -> list[tuple[str, int]]:
    """Rows that each kernel shuffles or broadcasts, by name; grids, slabs and rectangles for so many workers of one speed. Results in place cost 2 r s, as in the method."""
    side = lambda f: max(1, f)
    up = lambda x, y: -(-x // y)
    g, third, fifth = side(isqrt(m + 4) - 2), side(isqrt(m // 3)), side(isqrt(m // 5))
    resident = lambda rows, cols: 2 * r * s + nnz_a * cols + nnz_b * rows
    p1 = max(d for d in range(1, isqrt(workers) + 1) if workers % d == 0)
    square = isqrt(workers)
    packed = packed_rectangles(r, s, [1] * workers)
    partial = min(nnz_a * nnz_b // max(t, 1), r * s * t)
    return [
        ("resident", resident(up(r, g), up(s, g))),
        ("third", resident(up(r, third), up(s, third))),
        ("fifth", resident(up(r, fifth), up(s, fifth))),
        ("inner_join", nnz_a + nnz_b + partial),
        ("broadcast", workers * nnz_b + partial),
        ("slabs", resident(workers, 1)),
        ("grid", resident(p1, workers // p1)),
        ("weighted_grid", resident(p1, workers // p1)),
        ("shifted", resident(square, square)),
        ("rectangles", 2 * r * s + sum(nnz_a * (x[1] - x[0]) // r + nnz_b * (x[3] - x[2]) // s for x in packed)),
        ("inner_split", nnz_a + nnz_b + workers * r * s),
    ]


def choose_kernel(r: int, t: int, s: int, nnz_a: int, nnz_b: int, m: int, workers: int = 8) -> str:
    """The kernel of least volume among those whose result fits the memory in chunks: those with fixed parts need a part's share of C within m tiles a worker."""
    fits = {"resident", "third", "fifth", "inner_join"} | ({"broadcast"} if nnz_b <= m else set()) | ({"inner_split"} if r * s <= m else set())
    fits |= {"slabs", "grid", "weighted_grid", "rectangles"} if -(-r * s // workers) <= m else set()
    fits |= {"shifted"} if -(-r * s // isqrt(workers) ** 2) <= m else set()
    return min((x for x in cost_table(r, t, s, nnz_a, nnz_b, m, workers) if x[0] in fits), key=lambda x: (x[1], x[0]))[0]


def freivalds(a: DataFrame, b: DataFrame, c: DataFrame, rounds: int = 2) -> DataFrame:
    """(probe, bad): rows where C*x differs from A*(B*x), for pseudo-random 0/1 vectors x. Two matrix-vector products each, no product of matrices."""
    probe = F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("probe")
    bit = F.pmod(F.xxhash64("j", "probe"), F.lit(2))
    bx = b.select("k", "j", "u", probe).groupBy("probe", "k").agg(F.sum(F.col("u") * bit).alias("y"))
    ax = a.join(bx, "k").groupBy("probe", "i").agg(F.sum(F.col("v") * F.col("y")).alias("mine"))
    cx = c.select("i", "j", "c", probe).groupBy("probe", "i").agg(F.sum(F.col("c") * bit).alias("other"))
    both = ax.join(cx, ["probe", "i"], "full")
    return both.groupBy("probe").agg(F.sum(F.when(F.coalesce("mine", F.lit(0)) != F.coalesce("other", F.lit(0)), 1).otherwise(0)).alias("bad"))
