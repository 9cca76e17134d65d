"""Near copies: documents whose sets of word shingles have a Jaccard similarity of at least 4/5, found without loss.

A shingle is `WIDTH` consecutive words, ASCII case ignored, as a 64-bit hash; a text of fewer words is one shingle, a text without words has none.
Documents link if 5 |A and B| >= 4 |A or B|, or if both sets are empty; linked ones are of one component.

Two joins find the links; both end in the same verification on the texts. SimHash: the fingerprints of the sets meet in the trie self-join of `simhash` at its two
differing bits; what it proposes and the texts confirm, links. At 0.8 most pairs differ in more bits, so a second, exact join finds the links that it leaves, among
sets that it has not brought into one component.

Exact join: equal sets are merged first. Of n shingles in one fixed order, two sets that link share one of their first n - ceil(4n/5) + 1, so only those are
shuffled. The order puts shingles last that many documents share; any order is right, this one keeps the lists of a shingle short. At their first common shingle, the
i-th of A and the j-th of B counted from 0, sets that link still have min(|A| - i, |B| - j) >= 4 (|A| + |B|) / 9, so no other pairs of a list are met: a passage that many
documents share brings together only those that are little else. Each list's members are compared with its smallest member; then, in lists that still hold several components, all members of different components are compared.
Pairs inside a component are never listed, so a group of near copies costs rows in proportion to its size.

Pairs are first compared by fingerprints, bit k of which is the parity of the shingles whose hash ends in k. Every bit in which two fingerprints differ needs a shingle
that one set alone has, and sets that link differ in at most (|A| + |B|) / 9 shingles; so a pair over that budget of differing bits is dropped, without loss.
A fingerprint has two bits or more a shingle; the longer of a pair is folded to the length of the shorter. What is left is verified on the texts.

Defined results: null text counts as empty; of a component one row stays, that of the smallest id (null ids last), then text hash, then row number;
extra columns are kept; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilestar.llm import wordhash
from tilestar.llm.components import components
from tilestar.runtime import Scratch, kept_in_workers

#: Shingle width in words; the similarity is 4/5.
WIDTH = 5
#: Shingles counted at once, the least count reported, and the most shingles that the order tells apart by count; right results do not depend on them.
CHUNK, OFTEN, ORDERED = 1 << 20, 4, 1 << 17
#: Pairs given out at once.
PAIRS = 1 << 18
#: Bits of a fingerprint, at least and at most; more shingles than half of that share bits, which drops fewer pairs and loses none.
FEWEST, MOST = 64, 1 << 16
#: Odd multiplier that mixes a hash before its bits are counted, and hashes whose bits are counted at once.
MIX, SIMHASH_CHUNK = np.uint64(0x9E3779B97F4A7C15), 1 << 16


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct hashes of a text's shingles."""
    data = (text or "").encode("utf-8", "surrogatepass").lower()
    h = wordhash.words(data)[2] if data else np.zeros(0, np.uint64)
    return np.unique(wordhash.windows(h, min(width, len(h)))) if len(h) else h


def linked(a: np.ndarray, b: np.ndarray) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 5 * both >= 4 * (len(a) + len(b) - both)


def parity(s: np.ndarray) -> bytes:
    """Fingerprint of a set of hashes: the parities of how many end in each number."""
    bits = min(max(FEWEST, 1 << (2 * len(s)).bit_length()), MOST)
    return np.packbits(np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1, bitorder="little").tobytes()


def differing(a: bytes, b: bytes) -> int:
    """Differing bits of two fingerprints at the length of the shorter: at most the number of hashes that one set alone has."""
    x, y = (np.frombuffer(v, np.uint64) for v in (a, b))
    n = min(len(x), len(y))
    x, y = (np.bitwise_xor.reduce(v.reshape(-1, n), axis=0) for v in (x, y))
    return int(np.bitwise_count(x ^ y).sum())


def simhash_of(s: np.ndarray) -> int:
    """SimHash of a set of hashes, signed: bit k is set if it is set in over half of them; 0 for none."""
    count = np.zeros(64, np.int64)
    for k in range(0, len(s), SIMHASH_CHUNK):
        h = s[k : k + SIMHASH_CHUNK]
        h = (h ^ (h >> np.uint64(31))) * MIX  # a run's hash is a sum, whose low bits depend on low bits alone
        count += np.unpackbits((h ^ (h >> np.uint64(29))).view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * count > len(s)).view(np.int64)[0])


def prefix(s: np.ndarray, common: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The first n - ceil(4n/5) + 1 of n shingles, in order of (count, hash); common: sorted hashes that have a count, all others count zero."""
    rank = np.zeros(len(s), np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, s), len(common) - 1)
        rank = np.where(common[at] == s, count[at], 0)
    return s[np.lexsort((s, rank))[: len(s) - (4 * len(s) + 4) // 5 + 1]]


def numbered(df: DataFrame, scratch: Scratch) -> DataFrame:
    """df, written, with a number for each row in __row."""
    return scratch.save(df.withColumn("__row", F.monotonically_increasing_id()), "numbered")


def first_of(id_col: str, text: str):
    """What a component's rows are ordered by; its field `row` is the row's number."""
    ident = F.col(id_col).cast("bigint")
    return F.struct(ident.isNull().alias("none"), ident.alias("id"), F.xxhash64(F.col(text).cast("string")).alias("hash"), F.col("__row").alias("row"))


def _marks(rows: DataFrame) -> DataFrame:
    """rows: (row, text). (row, key of the set, its size, fingerprint and SimHash, shingles that are frequent in a part of the table with their counts)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, sizes, marks, prints, often, held, n = [], [], [], [], [], [], 0
            for k, t in enumerate(b.column(1)):
                s = shingles(t.as_py())
                sizes.append(len(s))
                marks.append(parity(s))
                prints.append(simhash_of(s))
                keys.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                held.append(s)
                n += len(s)
                found = []
                if n > CHUNK or k == b.num_rows - 1:
                    h, count = np.unique(np.concatenate(held), return_counts=True)
                    found = [{"h": x, "n": c} for x, c in zip(h[count >= OFTEN].view(np.int64).tolist(), count[count >= OFTEN].tolist(), strict=True)]
                    held, n = [], 0
                often.append(found)
            kind = pa.list_(pa.struct([("h", pa.int64()), ("n", pa.int64())]))
            cols = [b.column(0), pa.array(keys, pa.binary()), pa.array(sizes, pa.int64()), pa.array(marks, pa.binary()), pa.array(prints, pa.int64()), pa.array(often, kind)]
            yield pa.RecordBatch.from_arrays(cols, names=["row", "key", "size", "mark", "print", "often"])

    return rows.mapInArrow(run, "row bigint, key binary, size bigint, mark binary, print bigint, often array<struct<h: bigint, n: bigint>>")


def _postings(rows: DataFrame, common: np.ndarray, count: np.ndarray) -> DataFrame:
    """rows: (node, text). (h, node, size, pos) for each shingle of each prefix."""
    order = kept_in_workers(rows.sparkSession, (common, count))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            h, node, size, pos, held = [], [], [], [], 0
            for k, (i, t) in enumerate(zip(b.column(0).to_pylist(), b.column(1), strict=True)):
                s = shingles(t.as_py())
                if len(s):
                    p = prefix(s, *order())
                    h.append(p)
                    node.append(np.full(len(p), i, np.int64))
                    size.append(np.full(len(p), len(s), np.int64))
                    pos.append(np.arange(len(p)))
                    held += len(p)
                if h and (held > CHUNK or k == b.num_rows - 1):
                    cols = [np.concatenate(h).view(np.int64), *map(np.concatenate, (node, size, pos))]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["h", "node", "size", "pos"])
                    h, node, size, pos, held = [], [], [], [], 0

    return rows.mapInArrow(run, "h bigint, node bigint, size bigint, pos bigint")


def _within_budget(pairs: DataFrame, marks: DataFrame) -> DataFrame:
    """The pairs (a, b) whose fingerprints in marks (row, size, mark) differ in at most (|A| + |B|) / 9 bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            both = zip(b.column(2).to_pylist(), b.column(3).to_pylist(), b.column(4).to_pylist(), strict=True)
            ok = [9 * differing(x, y) <= total for total, x, y in both]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))

    side = lambda name: marks.select(F.col("row").alias(name), F.col("size").alias(f"{name}_size"), F.col("mark").alias(f"{name}_mark"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", (F.col("a_size") + F.col("b_size")).alias("total"), "a_mark", "b_mark")
    return both.mapInArrow(run, "a bigint, b bigint")


def _verified(pairs: DataFrame, rows: DataFrame, marks: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """The pairs (a, b) of `pairs` that link by their texts in rows (node, text)."""
    pairs = scratch.save(pairs, f"{name}_met")
    nodes = scratch.save(pairs.select(F.explode(F.array("a", "b")).alias("row")).distinct(), f"{name}_rows")
    own = scratch.save(marks.select("row", "size", "mark").join(scratch.small(nodes, f"{name}_rows"), "row"), f"{name}_marks")
    pairs = scratch.save(_within_budget(pairs, own), f"{name}_pairs")
    scratch.drop(f"{name}_met", f"{name}_rows", f"{name}_marks")
    nodes = scratch.save(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct(), f"{name}_nodes")
    texts = scratch.save(rows.join(scratch.small(nodes, f"{name}_nodes"), "node"), f"{name}_texts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            last, own, ok = None, None, []
            for i, x, y in zip(b.column(0).to_pylist(), b.column(2), b.column(3), strict=True):
                if i != last:
                    last, own = i, shingles(x.as_py())
                ok.append(linked(own, shingles(y.as_py())))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))

    both = pairs.join(texts.select(F.col("node").alias("a"), F.col("text").alias("x")), "a").join(texts.select(F.col("node").alias("b"), F.col("text").alias("y")), "b")
    edges = scratch.save(both.select("a", "b", "x", "y").mapInArrow(run, "a bigint, b bigint"), f"{name}_edges")
    scratch.drop(f"{name}_pairs", f"{name}_nodes", f"{name}_texts")
    return edges


def _across(lists: DataFrame) -> DataFrame:
    """lists: (h, node, size, pos, root, lead). Pairs of one list, of different roots, that can link, without those of its lead."""

    def pairs(node: np.ndarray, size: np.ndarray, pos: np.ndarray, root: np.ndarray) -> Iterator[pa.RecordBatch]:
        order = np.argsort(size, kind="stable")
        node, size, pos, root = node[order], size[order], pos[order], root[order]
        most = (5 * size - 9 * pos) // 4  # the largest set that one may link with
        ends, out, held = np.searchsorted(size, most, side="right"), [], 0
        for i in np.flatnonzero(ends > np.arange(1, len(node) + 1)).tolist():
            s = slice(i + 1, ends[i])
            other = node[s][(root[s] != root[i]) & (most[s] >= size[i])]
            out.append(np.stack([np.minimum(other, node[i]), np.maximum(other, node[i])]))
            held += len(other)
            if held > PAIRS:
                a, b = np.concatenate(out, axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])
                out, held = [], 0
        if held:
            a, b = np.concatenate(out, axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = None
        for b in batches:
            x = np.stack([c.to_numpy() for c in b.columns])
            x = x if rest is None else np.concatenate([rest, x], axis=1)
            if not x.shape[1]:
                continue
            starts = np.append(0, np.flatnonzero(np.diff(x[0])) + 1)
            for lo, hi in zip(starts[:-1], starts[1:], strict=True):
                yield from pairs(*x[1:, lo:hi])
            rest = x[:, starts[-1] :]
        if rest is not None and rest.shape[1]:
            yield from pairs(*rest[1:])

    tasks = int(lists.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = lists.filter("node <> lead").select("h", "node", "size", "pos", "root").repartition(tasks, "h").sortWithinPartitions("h")
    return dealt.mapInArrow(run, "a bigint, b bigint").distinct()


def by_trie(rows: DataFrame, marks: DataFrame, scratch: Scratch) -> DataFrame:
    """rows: (node, text), no set twice; marks: (row, size, mark, print). Edges (a, b) that the trie of SimHash fingerprints proposes and the texts confirm.

    Sets of one fingerprint are compared with their smallest; those of linked fingerprints by the smallest of either.
    """
    from tilestar.llm import simhash

    own = scratch.save(marks.select(F.col("row").alias("node"), "print").join(rows.select("node"), "node", "left_semi"), "prints")
    lead = scratch.save(own.groupBy("print").agg(F.min("node").alias("lead")), "print_lead")
    of = scratch.small(lead, "print_lead")
    same = own.join(of, "print").filter("node <> lead").select(F.col("lead").alias("a"), F.col("node").alias("b"))
    met = scratch.save(simhash.links(lead.select(F.col("print").alias("fp"))).distinct(), "print_met")
    side = lambda name: of.select(F.col("print").alias(name), F.col("lead").alias(f"{name}_lead"))
    near = met.join(side("a"), "a").join(side("b"), "b").select(F.least("a_lead", "b_lead").alias("a"), F.greatest("a_lead", "b_lead").alias("b"))
    edges = _verified(same.union(near), rows, marks, scratch, "trie")
    scratch.drop("prints", "print_lead", "print_met")
    return edges


def links(rows: DataFrame, marks: DataFrame, common: np.ndarray, count: np.ndarray, scratch: Scratch) -> DataFrame:
    """rows: (node, text), no set twice; marks: (row, size, mark, print). Edges (a, b) whose components are those of all links."""
    found = by_trie(rows, marks, scratch)
    trie = scratch.save(components(found, scratch), "trie_stars")
    post = scratch.save(_postings(rows, common, count), "post")
    lead = post.groupBy("h").agg(F.min(F.struct("node", "size", "pos")).alias("lead"), F.max("node").alias("last")).filter("lead.node < last")
    lead = scratch.save(lead.select("h", F.col("lead.node").alias("lead"), F.col("lead.size").alias("lead_size"), F.col("lead.pos").alias("lead_pos")), "lead")
    shared = scratch.save(post.join(scratch.small(lead, "lead"), "h"), "shared")
    scratch.drop("post", "lead")
    near = shared.filter("node <> lead and 9 * least(size - pos, lead_size - lead_pos) >= 4 * (size + lead_size)")
    near = near.select(F.col("lead").alias("a"), F.col("node").alias("b")).distinct()
    for end in "ab":  # pairs of one component of the trie's are linked already
        near = near.join(scratch.small(trie, "trie_stars").select(F.col("node").alias(end), F.col("root").alias(f"{end}_root")), end, "left")
    near = near.filter("coalesce(a_root, a) <> coalesce(b_root, b)").select("a", "b")
    edges = found.union(_verified(near, rows, marks, scratch, "first"))
    stars = components(edges, scratch).withColumnRenamed("node", "star")
    rooted = shared.join(stars, F.col("node") == F.col("star"), "left").withColumn("root", F.coalesce("root", "node"))
    rooted = scratch.save(rooted.select("h", "node", "size", "pos", "root", "lead"), "rooted")
    mixed = scratch.save(rooted.groupBy("h").agg(F.min("root").alias("low"), F.max("root").alias("high")).filter("low <> high").select("h"), "mixed")
    more = _verified(_across(rooted.join(scratch.small(mixed, "mixed"), "h")), rows, marks, scratch, "more")
    scratch.drop("shared", "rooted", "mixed", "trie_stars")
    return edges.union(more)


def keep_one(df: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """One row of df for each component."""
    scratch = Scratch(df.sparkSession, "nearcopies")
    rows = numbered(df, scratch)
    texts = rows.select(F.col("__row").alias("node"), F.col(text).cast("string").alias("text"))
    marks = scratch.save(_marks(texts), "marks")
    often = marks.select(F.explode("often").alias("x")).groupBy("x.h").agg(F.sum("x.n").alias("n")).orderBy(F.desc("n"), "h").limit(ORDERED).toPandas().sort_values("h")
    own = rows.select(first_of(id_col, text).alias("first"))
    sets = own.join(marks.select("row", "key"), F.col("first.row") == F.col("row")).groupBy("key").agg(F.min("first").alias("first"))
    sets = scratch.save(sets.select(F.col("first.row").alias("node"), "first"), "sets")
    nodes = scratch.save(sets.select("node"), "nodes")
    common = often["h"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(common)
    distinct = scratch.save(texts.join(scratch.small(nodes, "nodes"), "node"), "distinct")
    stars = components(links(distinct, marks, common[order], often["n"].to_numpy(np.int64)[order], scratch), scratch, "all").withColumnRenamed("node", "star")
    best = sets.join(stars, F.col("node") == F.col("star"), "left").groupBy(F.coalesce("root", "node")).agg(F.min("first").alias("first"))
    kept = scratch.save(best.select(F.col("first.row").alias("__row")), "kept")
    scratch.drop("marks", "sets", "nodes", "distinct")
    return rows.join(scratch.small(kept, "kept"), "__row", "left_semi").drop("__row")
