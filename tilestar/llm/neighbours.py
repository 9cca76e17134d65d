"""Approximate nearest neighbours: an NN-descent graph, searched greedily.

Index: equal vectors are one node. Every node keeps its K nearest nodes found so far. The graph starts from random-projection trees (leaves compared in full; a leaf that is
too large is split between two of its members, as often as it takes) and improves in rounds: each node brings together its neighbours and those it is a neighbour of, all pairs of which at least one is new are compared, and a
pair is reported only to an end whose K-th distance it beats. Rounds end when few entries of the lists are new (STILL). Every row is indexed; only the upper planes of the
trees come from a bounded sample, of SAMPLE nodes.

Search: a query starts at its own node's list and expands the nearest unexpanded nodes of its beam, all queries together, until no beam has
any; the best are ranked by the exact distance on the original vectors. Distances in the graph are on vectors quantised to 8 bits a component.

Bounds that belong to the method: K forward and K reverse neighbours meet in a round (the nearest ones); a node that is a neighbour of more is no less indexed, as
each of those has it in its own list.

Defined results: rows take no part if the vector is null, zero, or holds null or non-finite components, or the id is null; vectors of different lengths have no distance, so
each length is searched on its own; repeated rows of
an id count once (the smallest vector); queries with fewer candidates than asked get all; ties go to the smaller id; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tilestar.runtime import Scratch

#: Neighbours a node keeps; trees; rows of a leaf, twice that at most; nodes sampled for planes; share of new neighbours at which rounds end.
K, TREES, LEAF, SAMPLE, STILL = 32, 4, 512, 8192, 0.02
#: Beam of a search.
BEAM = 256
CODED = "node bigint, code binary, scale double, square double"


def _vectors(df: DataFrame, id_col: str, vector: str) -> DataFrame:
    """(vec_id, v, dim) of the rows that take part."""
    v = F.col("v")
    rows = df.select(F.col(id_col).cast("bigint").alias("vec_id"), F.col(vector).alias("v")).filter("vec_id is not null and v is not null")
    sound = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return rows.filter(sound).groupBy("vec_id").agg(F.min("v").alias("v")).withColumn("dim", F.size("v"))


def _nodes(vectors: DataFrame, most: int) -> DataFrame:
    """(node, v, ids): equal vectors together; ids: the `most` smallest. A large group is cut down in parts first."""
    few = lambda c: F.slice(F.sort_array(c), 1, most)
    part = vectors.groupBy("v", F.pmod(F.xxhash64("vec_id"), F.lit(64)).alias("part")).agg(few(F.collect_list("vec_id")).alias("ids"))
    return part.groupBy("v").agg(few(F.flatten(F.collect_list("ids"))).alias("ids")).select(F.col("ids")[0].alias("node"), "v", "ids")


def _matrix(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten(), np.float64).reshape(len(column), -1)


def _codes(nodes: DataFrame) -> DataFrame:
    """Vectors quantised to bytes, each with its own scale."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = _matrix(b.column(1))
            scale = np.abs(x).max(axis=1) / 127
            code = np.rint(x / scale[:, None]).astype(np.int8)
            square = (code.astype(np.int64) ** 2).sum(axis=1) * scale * scale
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in code], pa.binary()), pa.array(scale), pa.array(square)], names=["node", "code", "scale", "square"])

    return nodes.select("node", "v").mapInArrow(run, CODED)


def _bytes(column: pa.Array) -> np.ndarray:
    n = len(column)
    return np.frombuffer(b"".join(column.to_pylist()), np.int8).reshape(n, -1).astype(np.float32) if n else np.zeros((0, 1), np.float32)


def _distances(code: np.ndarray, scale: np.ndarray, square: np.ndarray, code2: np.ndarray, scale2: np.ndarray, square2: np.ndarray) -> np.ndarray:
    """Squared distances; products of codes are whole numbers, so a pair gets one value from either side."""
    return np.maximum(square[:, None] + square2 - 2 * (scale[:, None] * scale2) * (code @ code2.T), 0)


def _runs(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.RecordBatch]:
    """Re-cuts sorted batches so that none ends inside a group of equal first `keys` columns. A group is of bounded size here."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        cols = [b.column(k).to_numpy() for k in range(keys)]
        change = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        if held:
            tail = held[-1]
            same = all(tail.column(k)[-1].as_py() == b.column(k)[0].as_py() for k in range(keys))
            cut = (int(change[0]) if len(change) else b.num_rows) if same else 0
            held.append(b.slice(0, cut))
            if cut == b.num_rows:
                continue
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            b, change, held = b.slice(cut), change[change > cut] - cut, []
        last = int(change[-1]) if len(change) else 0
        if last:
            yield b.slice(0, last)
        held = [b.slice(last)]
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def _groups(b: pa.RecordBatch, keys: int) -> Iterator[tuple[int, int]]:
    cols = [b.column(k).to_numpy() for k in range(keys)]
    edge = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
    yield from zip([0, *edge.tolist()], [*edge.tolist(), b.num_rows], strict=True)


def _best(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]], k: int) -> pa.RecordBatch:
    """The k nearest found for each u, each once."""
    u, w, d = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.lexsort((w, d, u))
    u, w, d = u[order], w[order], d[order]
    new = np.ones(len(u), bool)
    new[1:] = (u[1:] != u[:-1]) | (w[1:] != w[:-1]) | (d[1:] != d[:-1])
    u, w, d = u[new], w[new], d[new]
    start = np.flatnonzero(np.concatenate(([True], u[1:] != u[:-1]))) if len(u) else np.zeros(0, np.int64)
    nth = np.arange(len(u)) - np.repeat(start, np.diff(np.append(start, len(u))))
    ok = nth < k
    return pa.RecordBatch.from_arrays([pa.array(u[ok]), pa.array(w[ok]), pa.array(d[ok])], names=["u", "w", "d"])


def _gathered(parts: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]], k: int) -> Iterator[pa.RecordBatch]:
    held, count = [], 0
    for part in parts:
        held.append(part)
        count += len(part[0])
        if count > 1 << 18:
            yield _best(held, k)
            held, count = [], 0
    if held:
        yield _best(held, k)


def _planes(sample: np.ndarray, depth: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """A perfect binary tree of planes, each through the median of its part of the sample along the line of two of its points."""
    rng = np.random.default_rng(seed)
    size = (1 << depth) - 1
    plane, bound = np.zeros((size, sample.shape[1])), np.zeros(size)
    parts = {0: np.arange(len(sample))}
    for k in range(size):
        own = parts.pop(k)
        if len(own) >= 2:
            a, b = rng.choice(own, 2, replace=False)
            plane[k] = sample[a] - sample[b]
        else:
            plane[k] = rng.normal(size=sample.shape[1])
        at = sample[own] @ plane[k]
        bound[k] = np.median(at) if len(own) else 0.0
        if 2 * k + 2 < size:
            parts[2 * k + 1], parts[2 * k + 2] = own[at <= bound[k]], own[at > bound[k]]
    return plane, bound


def _split(leaves: DataFrame, scratch: Scratch, tasks: int) -> DataFrame:
    """leaves (leaf, node, code, ...): those of more than 2 * LEAF rows are split, each member to the nearer of two members drawn by hash, equally near ones by hash, until none is too large."""
    done, turn = [], 0
    while True:
        sizes = leaves.groupBy("leaf").agg(F.count(F.lit(1)).alias("n"))
        large = scratch.save(sizes.filter(F.col("n") > 2 * LEAF).select(F.col("leaf").alias("large")), f"large{turn}")
        if large.isEmpty():
            return functools.reduce(DataFrame.unionByName, done, leaves)
        marked = leaves.join(scratch.small(large, f"large{turn}"), F.col("leaf") == F.col("large"), "left")
        done.append(marked.filter("large is null").drop("large"))
        rest = marked.filter("large is not null").drop("large")
        draw = F.xxhash64("node", F.lit(turn))
        own = F.struct(draw.alias("draw"), "code", "scale", "square")
        pivots = rest.groupBy("leaf").agg(F.min(own).alias("a"), F.max(own).alias("b"))
        fields = [f"{p}.{c}" for p in "ab" for c in ("code", "scale", "square")]
        pivots = scratch.save(pivots.select(F.col("leaf").alias("large"), *(F.col(f).alias(f.replace(".", "_")) for f in fields)), f"pivots{turn}")
        met = rest.join(scratch.small(pivots, f"pivots{turn}"), F.col("leaf") == F.col("large")).withColumn("coin", F.pmod(draw, F.lit(2)))

        def sides(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x, scale, square = _bytes(b.column("code")), b.column("scale").to_numpy(), b.column("square").to_numpy()
                d = [
                    b.column(f"{p}_square").to_numpy() + square - 2 * scale * b.column(f"{p}_scale").to_numpy() * np.einsum("ij,ij->i", x, _bytes(b.column(f"{p}_code")), dtype=np.float64)
                    for p in "ab"
                ]
                right = np.where(d[0] == d[1], b.column("coin").to_numpy(), d[1] < d[0]).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(2 * b.column("leaf").to_numpy() + right), *(b.column(c) for c in ("node", "code", "scale", "square"))], names=["leaf", "node", "code", "scale", "square"])

        # leaves of later turns get numbers of their own: the number doubles, and settled ones leave the table
        leaves = scratch.save(met.mapInArrow(sides, "leaf bigint, " + CODED), f"leaves{turn + 1}")
        done[-1] = done[-1].withColumn("leaf", F.xxhash64("leaf", F.lit(turn)))
        leaves = leaves.repartition(tasks)
        turn += 1


def _start(nodes: DataFrame, codes: DataFrame, n: int, k: int, tasks: int, scratch: Scratch) -> DataFrame:
    """(u, w, d) from random-projection trees."""
    drawn = nodes.orderBy(F.xxhash64("node"), "node").limit(SAMPLE).select("v").collect()  # the documented bound
    sample = np.array([r[0] for r in drawn], float) if drawn else np.zeros((0, 1))
    depth = max(0, min(int(np.ceil(np.log2(max(n / LEAF, 1)))), int(np.log2(max(len(sample) / 8, 1)))))
    trees = [_planes(sample, depth, t) for t in range(TREES)]

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _bytes(b.column(1)).astype(np.float64) * b.column(2).to_numpy()[:, None]
            for t, (plane, bound) in enumerate(trees):
                at = np.zeros(len(x), np.int64)
                for _ in range(depth):
                    at = 2 * at + 1 + (np.einsum("ij,ij->i", x, plane[at]) > bound[at])
                yield pa.RecordBatch.from_arrays([pa.array(at * TREES + t), *b.columns], names=["leaf", *b.schema.names])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
            for b in _runs(batches, 1):
                node, code, scale, square = b.column(1).to_numpy(), _bytes(b.column(2)), b.column(3).to_numpy(), b.column(4).to_numpy()
                for lo, hi in _groups(b, 1):
                    s = slice(lo, hi)
                    d = _distances(code[s], scale[s], square[s], code[s], scale[s], square[s])
                    np.fill_diagonal(d, np.inf)
                    m = min(k, len(d) - 1)
                    if m > 0:
                        j = np.argpartition(d, m - 1, axis=1)[:, :m]
                        yield np.repeat(node[s], m), node[s][j.ravel()], np.take_along_axis(d, j, 1).ravel()

        yield from _gathered(parts(), k)

    leaves = scratch.save(codes.mapInArrow(spread, "leaf bigint, " + CODED), "leaves0")
    dealt = _split(leaves, scratch, tasks).repartition(tasks, "leaf").sortWithinPartitions("leaf", "node")
    return dealt.mapInArrow(compare, "u bigint, w bigint, d double")


def _merged(edges: DataFrame, k: int, tasks: int) -> DataFrame:
    """edges (u, w, d, fresh) -> (u, near: the k nearest as (d, w, fresh)), each neighbour once; an old edge stays old."""
    once = edges.repartition(tasks, "u").groupBy("u", "w").agg(F.min("d").alias("d"), F.min("fresh").alias("fresh"))
    return once.groupBy("u").agg(F.slice(F.sort_array(F.collect_list(F.struct("d", "w", "fresh"))), 1, k).alias("near"))


def _local_join(graph: DataFrame, codes: DataFrame, k: int, tasks: int) -> DataFrame:
    """(u, w, d) between neighbours of a common node, where it beats u's list."""
    edge = graph.select("u", F.explode("near").alias("e")).select("u", "e.w", "e.d", "e.fresh")
    nearest = Window.partitionBy("w").orderBy("d", "u")
    back = edge.withColumn("nth", F.row_number().over(nearest)).filter(F.col("nth") <= k).select(F.col("w").alias("x"), F.col("u").alias("m"), "fresh")
    meet = edge.select(F.col("u").alias("x"), F.col("w").alias("m"), "fresh").union(back).groupBy("x", "m").agg(F.max("fresh").alias("fresh"))
    last = graph.select(F.col("u").alias("m"), F.when(F.size("near") >= k, F.element_at("near", -1)["d"]).otherwise(float("inf")).alias("worst"))
    known = codes.withColumnRenamed("node", "m").join(last, "m", "left")
    rows = meet.join(known, "m").select("x", "m", "fresh", "code", "scale", "square", F.coalesce("worst", F.lit(float("inf"))).alias("worst"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def parts() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
            for b in _runs(batches, 1):
                m, fresh = b.column(1).to_numpy(), b.column(2).to_numpy() > 0
                code, scale, square, worst = _bytes(b.column(3)), *(b.column(c).to_numpy() for c in (4, 5, 6))
                for lo, hi in _groups(b, 1):
                    s = slice(lo, hi)
                    new = np.flatnonzero(fresh[s]) + lo
                    if not len(new) or hi - lo < 2:
                        continue
                    d = _distances(code[new], scale[new], square[new], code[s], scale[s], square[s])
                    d[np.arange(len(new)), new - lo] = np.inf
                    i, j = np.nonzero(d < worst[new][:, None])
                    yield m[new[i]], m[s][j], d[i, j]
                    i, j = np.nonzero(d < worst[s])
                    yield m[s][j], m[new[i]], d[i, j]

        yield from _gathered(parts(), k)

    return rows.repartition(tasks, "x").sortWithinPartitions("x").mapInArrow(run, "u bigint, w bigint, d double")


def build(nodes: DataFrame, codes: DataFrame, scratch: Scratch, k: int = K) -> DataFrame:
    """The graph: (u, near), near sorted by (d, w)."""
    tasks = int(nodes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    n = nodes.count()
    graph = scratch.save(_merged(_start(nodes, codes, max(n, 1), k, tasks, scratch).withColumn("fresh", F.lit(1)), k, tasks), "graph0")
    for turn in itertools.count(1):
        found = _local_join(graph, codes, k, tasks).withColumn("fresh", F.lit(1))
        old = graph.select("u", F.explode("near").alias("e")).select("u", "e.w", "e.d", F.lit(0).alias("fresh"))
        graph = scratch.save(_merged(old.unionByName(found), k, tasks), f"graph{turn}")
        scratch.drop(f"graph{turn - 1}")
        fresh, every = graph.agg(F.sum(F.aggregate("near", F.lit(0), lambda a, e: a + e["fresh"])), F.sum(F.size("near"))).first()
        if (fresh or 0) <= STILL * (every or 0):
            break
    return graph


def _search(graph: DataFrame, codes: DataFrame, starts: DataFrame, scratch: Scratch, beam: int) -> DataFrame:
    """starts (q): distinct query nodes. (q, x): the nodes of each final beam."""
    tasks = int(graph.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    near = graph.select(F.col("u").alias("x"), F.transform("near", lambda e: e["w"]).alias("next"))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _runs(batches, 1):
            q, x = b.column(0).to_numpy(), b.column(1).to_numpy()
            code, scale, square = _bytes(b.column(2)), b.column(3).to_numpy(), b.column(4).to_numpy()
            d = np.empty(len(q))
            for lo, hi in _groups(b, 1):
                own = lo + int(np.flatnonzero(x[lo:hi] == q[lo])[0])
                s, o = slice(lo, hi), slice(own, own + 1)
                d[s] = _distances(code[o], scale[o], square[o], code[s], scale[s], square[s])[0]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(d)], names=["q", "x", "d"])

    def reach(front: DataFrame) -> DataFrame:
        """Distances of the neighbours of `front` (q, x)."""
        seen = front.join(near, "x").select("q", F.explode("next").alias("x")).union(front.select("q", F.col("q").alias("x"))).distinct()
        rows = seen.join(codes.withColumnRenamed("node", "x"), "x").select("q", "x", "code", "scale", "square")
        return rows.repartition(tasks, "q").sortWithinPartitions("q").mapInArrow(measure, "q bigint, x bigint, d double").withColumn("done", F.when(F.col("q") == F.col("x"), 1).otherwise(0))

    def best(rows: DataFrame) -> DataFrame:
        once = rows.repartition(tasks, "q").groupBy("q", "x").agg(F.min("d").alias("d"), F.max("done").alias("done"))
        top = once.groupBy("q").agg(F.slice(F.sort_array(F.collect_list(F.struct("d", "x", "done"))), 1, beam).alias("top"))
        return top.select("q", F.explode("top").alias("e")).select("q", "e.x", "e.d", "e.done")

    now = scratch.save(best(reach(starts.select("q", F.col("q").alias("x")))), "beam0")
    for step in itertools.count(1):
        front = now.filter("done = 0")
        if front.isEmpty():
            break
        old = now.withColumn("done", F.lit(1))
        now = scratch.save(best(old.unionByName(reach(front.select("q", "x")))), f"beam{step}")
        scratch.drop(f"beam{step - 1}")
    return now.select("q", "x")


def euclidean(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") - y.cast("double")), F.lit(0.0), lambda acc, x: acc + x * x))


def nearest(df: DataFrame, is_query: Column | str, top: int = 10, id_col: str = "vec_id", vector: str = "embedding", k: int = K, beam: int = BEAM) -> DataFrame:
    """(query_id, rank, vec_id, score): for each row that is_query (over vec_id) holds for, its `top` nearest other rows."""
    scratch = Scratch(df.sparkSession, "neighbours")
    vectors = scratch.save(_vectors(df, id_col, vector), "vectors")
    dims = [r[0] for r in vectors.select("dim").distinct().orderBy("dim").collect()]  # the lengths that occur, one as a rule
    parts = [_nearest(vectors.filter(F.col("dim") == dim).select("vec_id", "v"), is_query, top, k, beam, Scratch(df.sparkSession, f"neighbours-{dim}")) for dim in dims]
    if not parts:
        return df.sparkSession.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    return functools.reduce(DataFrame.unionByName, parts)


def _nearest(vectors: DataFrame, is_query: Column | str, top: int, k: int, beam: int, scratch: Scratch) -> DataFrame:
    nodes = scratch.save(_nodes(vectors, top + 1), "nodes")
    codes = scratch.save(_codes(nodes), "codes")
    graph = build(nodes, codes, scratch, max(k, top + 1))
    asked = vectors.filter(is_query).select(F.col("vec_id").alias("query_id"), "v").join(nodes.select("node", "v"), "v").select("query_id", "v", F.col("node").alias("q"))
    asked = scratch.save(asked, "asked")
    found = _search(graph, codes, asked.select("q").distinct(), scratch, max(beam, 2 * top))
    pairs = asked.join(found, "q").join(nodes.select(F.col("node").alias("x"), F.col("v").alias("w"), "ids"), "x")
    scored = pairs.select("query_id", euclidean(F.col("v"), F.col("w")).alias("score"), F.explode("ids").alias("vec_id")).filter("vec_id <> query_id")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id"))
    return scored.withColumn("rank", rank.cast("int")).filter(F.col("rank") <= top).select("query_id", "rank", "vec_id", "score")


def op3_neighbours(df: DataFrame) -> DataFrame:
    return nearest(df, "vec_id % 100 = 0")
