"""Near-duplicate documents by SimHash fingerprints and a binary trie self-join.

Fingerprint: bit k of 64 is set if it is set in over half of the XXH64 hashes of the text's word shingles (repeats count).
A text of fewer words than a shingle has its whole word sequence as one shingle; a text without words has fingerprint zero.
Fingerprints link at `bits` or fewer differing bits (0 to 2); linked ones are of one component, named by its smallest id.

Join: the distinct fingerprints form a binary trie. Pairs of nodes are traversed together from the root; each step down
adds the differing bit to the pair's error, and a pair over the budget is dropped. To spread the trie over machines, its first levels are chosen
so that they must agree: with at most 2 differing bits one of three blocks is equal, and of the rest again one of three, so each
fingerprint goes to nine sub-tries, keyed by the equal bits, and two that link meet in one of them at least.
A task reports for its sub-tries a spanning forest of the links it found, never all pairs, so a large group of near copies costs rows in proportion to its size.

Defined results: null text counts as empty; empties link with each other; repeated rows are one component; a null id takes no part in
naming a component, and the component of null ids alone is null; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilestar.llm.components import components
from tilestar.llm.nearcopies import first_of, numbered
from tilestar.runtime import Scratch

#: Fixed values of the contract: shingle width in words, hash seed, most differing bits.
WIDTH, SEED, BITS = 3, 42, 2
#: Hashes whose bits are counted at once; bounds memory on very long texts.
CHUNK = 1 << 16
#: Node pairs traversed at once; the rest waits on a stack.
FRONT = 1 << 18
#: Pairs of nodes with at most so many pairs of leaves are compared leaf by leaf.
LEAVES = 16


def fingerprint(text: str | None, width: int = WIDTH, seed: int = SEED) -> int:
    """Unsigned 64-bit SimHash of a text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII case and ASCII white space only
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    reach = min(width, len(words)) - 1
    one = xxhash.xxh64_intdigest
    n = len(words) - reach
    counts = np.zeros(64, np.int64)
    first, last = starts[:n].tolist(), ends[reach:].tolist()
    for k in range(0, n, CHUNK):
        h = np.array([one(joined[a:b], seed) for a, b in zip(first[k : k + CHUNK], last[k : k + CHUNK], strict=True)], dtype=">u8")
        counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > n).tobytes(), "big")


def fingerprints(df: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = WIDTH, seed: int = SEED) -> DataFrame:
    """(id, fp): fp is the fingerprint as a signed long."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t, width, seed) for t in b.column(1).to_pylist()), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], names=["id", "fp"])

    rows = df.select(F.col(id_col).cast("bigint").alias("id"), F.col(text).cast("string").alias("text"))
    return rows.mapInArrow(run, "id bigint, fp bigint")


def _blocks(n: int) -> list[tuple[int, int]]:
    """n bits cut in three: (first bit, length) from the top."""
    a, b = -(-n // 3), -(-(n - -(-n // 3)) // 2)
    return [(0, a), (a, b), (a + b, n - a - b)]


def _to_front(v: np.ndarray, n: int, at: int, length: int) -> np.ndarray:
    """The low n bits of v with the block [at, at+length), counted from their top, moved to their front; higher bits stay."""
    u = np.uint64
    ones = lambda k: u((1 << k) - 1)
    block = (v >> u(n - at - length)) & ones(length)
    front = (v >> u(n - at)) & ones(at) if at else np.zeros_like(v)
    tail = v & ones(n - at - length)
    rest = (front << u(n - at - length)) | tail
    high = (v >> u(n)) << u(n) if n < 64 else np.zeros_like(v)
    return high | (block << u(n - length)) | rest


def _views(v: np.ndarray) -> Iterator[tuple[int, int, np.ndarray]]:
    """Nine rearrangements of the bits: (number, equal bits at the top, values)."""
    for i, (at, length) in enumerate(_blocks(64)):
        w, left = _to_front(v, 64, at, length), 64 - length
        for j, (at2, length2) in enumerate(_blocks(left)):
            yield 3 * i + j, length + length2, _to_front(w, left, at2, length2)


TOP = [top for _, top, _ in _views(np.zeros(1, np.uint64))]


def _forest(pairs: list[tuple[np.ndarray, np.ndarray]], n: int) -> np.ndarray:
    """Smallest reachable index of each of n indices."""
    label = np.arange(n)
    a, b = (np.concatenate(x) for x in zip(*pairs, strict=True))
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, label):
            return label
        label = new


def trie_links(v: np.ndarray, top: int, budget: int) -> np.ndarray:
    """v: sorted distinct uint64. Labels of a forest that links all i, j with equal first `top` bits and at most `budget` differing bits."""
    n = len(v)
    u = np.uint64
    label, found, held = np.arange(n), [], 0
    starts = np.flatnonzero(np.concatenate(([True], (v[1:] >> u(64 - top)) != (v[:-1] >> u(64 - top))))) if n else np.zeros(0, np.int64)
    ends = np.append(starts[1:], n)
    many = ends - starts > 1
    # a node is a range of v; rows: node A, node B (equal or later), error so far, next bit
    stack = [np.stack([starts[many], ends[many], starts[many], ends[many], np.zeros(many.sum(), np.int64), np.full(many.sum(), 63 - top)])] if many.any() else []

    def fold() -> None:
        nonlocal label, found, held
        label = _forest([(np.arange(n), label), *found], n)
        found, held = [], 0

    while stack:
        f = stack.pop()
        if f.shape[1] > FRONT:
            stack += [f[:, : f.shape[1] // 2], f[:, f.shape[1] // 2 :]]
            continue
        small = (f[1] - f[0]) * (f[3] - f[2]) <= LEAVES
        leaf, f = f[:, small], f[:, ~small]
        if leaf.shape[1]:
            size = (leaf[1] - leaf[0]) * (leaf[3] - leaf[2])
            row = np.repeat(np.arange(leaf.shape[1]), size)
            k = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            wide = (leaf[3] - leaf[2])[row]
            a, b = leaf[0][row] + k // wide, leaf[2][row] + k % wide
            ok = (a < b) & (np.bitwise_count(v[a] ^ v[b]) <= budget)
            found.append((a[ok], b[ok]))
            held += int(ok.sum())
            if held > 4 * FRONT:
                fold()
        if not f.shape[1]:
            continue
        bit = f[5].astype(u)

        def middle(lo: np.ndarray, bit: np.ndarray) -> np.ndarray:
            return np.searchsorted(v, (v[lo] >> bit | u(1)) << bit)

        ma, mb = np.minimum(middle(f[0], bit), f[1]), np.minimum(middle(f[2], bit), f[3])
        same = f[0] == f[2]
        down = lambda a, b, c, d, e, keep: np.stack([a, b, c, d, f[4] + e, f[5] - 1])[:, keep & (a < b) & (c < d) & (f[4] + e <= budget)]
        yes = np.ones(f.shape[1], bool)
        nxt = np.concatenate([down(f[0], ma, f[2], mb, 0, yes), down(ma, f[1], mb, f[3], 0, yes), down(f[0], ma, mb, f[3], 1, yes), down(ma, f[1], f[2], mb, 1, ~same)], axis=1)
        nxt = nxt[:, (nxt[0] != nxt[2]) | (nxt[1] - nxt[0] > 1)]
        if nxt.shape[1]:
            stack.append(nxt)
    if found:
        fold()
    return label


def links(distinct: DataFrame, bits: int = BITS) -> DataFrame:
    """distinct: (fp) without repeats. Edges (a, b) between fingerprints whose components are those of all links."""
    if not 0 <= bits <= 2:
        raise ValueError("the sub-tries cover at most 2 differing bits")

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = b.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for k, top, w in _views(v):
                key = (w >> np.uint64(64 - top)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(v), k, np.int32)), pa.array(key), pa.array(v.view(np.int64))], names=["view", "key", "fp"])

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
        if not got:
            return
        view, fp = (np.concatenate(x) for x in zip(*got, strict=True))
        for k in range(9):
            own = fp[view == k].view(np.uint64)
            _, top, w = next(x for x in _views(own) if x[0] == k)
            order = np.argsort(w)
            label = trie_links(w[order], top, bits)
            i = np.flatnonzero(label != np.arange(len(label)))
            own = own[order].view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(own[i]), pa.array(own[label[i]])], names=["a", "b"])

    tasks = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = distinct.select("fp").mapInArrow(spread, "view int, key bigint, fp bigint").repartition(tasks, "view", "key")
    return dealt.select("view", "fp").mapInArrow(join, "a bigint, b bigint")


def classes(df: DataFrame, id_col: str = "doc_id", text: str = "text", width: int = WIDTH, seed: int = SEED, bits: int = BITS) -> DataFrame:
    """(id, fp, component_id) for every row of df."""
    scratch = Scratch(df.sparkSession, "simhash")
    marks = scratch.save(fingerprints(df, id_col, text, width, seed), "marks")
    distinct = scratch.save(marks.groupBy("fp").agg(F.min("id").alias("least")), "distinct")
    stars = components(links(distinct, bits), scratch)
    rooted = distinct.join(stars, F.col("fp") == F.col("node"), "left").select("fp", F.coalesce("root", "fp").alias("root"), "least")
    rooted = scratch.save(rooted, "rooted")
    names = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = scratch.save(rooted.join(names, "root").select(F.col("fp").alias("named_fp"), "component_id"), "named")
    scratch.drop("rooted", "distinct")
    return marks.join(scratch.small(named, "named"), F.col("fp") == F.col("named_fp"), "left").select("id", "fp", "component_id")


def keep_one(df: DataFrame, id_col: str = "doc_id", text: str = "text", **options: int) -> DataFrame:
    """One row of df for each component: that of the smallest id (null ids last), then text hash, then row number."""
    scratch = Scratch(df.sparkSession, "simhash")
    rows = numbered(df, scratch)
    group = classes(rows, "__row", text, **options).select("id", F.col("component_id").alias("group"))
    best = rows.select(first_of(id_col, text).alias("first")).join(group, F.col("first.row") == F.col("id")).groupBy("group").agg(F.min("first").alias("first"))
    kept = scratch.save(best.select(F.col("first.row").alias("__row")), "kept")
    return rows.join(scratch.small(kept, "kept"), "__row", "left_semi").drop("__row")


def op6_simhash(df: DataFrame) -> DataFrame:
    return classes(df).select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
