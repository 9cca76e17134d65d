"""Substring dedup: words that lie in a window of `window` words whose sequence starts anywhere else too.

Relative Lempel-Ziv parsing, with the corpus as its own reference. The reference is indexed by anchors: the smallest hash of an
8-word seed in each window is its anchor, so a passage gets the same anchors wherever it stands, and all windows of one anchor lie in the reference block of its seed. So a text is
parsed against every block that can hold a copy of any of its windows, and against no other.

1. Stretches with equal anchor and equal windows are copies as a whole. Anchors that occur once cannot lie in a repeated window, so most of the text drops out here.
2. The stretches of a block that differ - at the ends of copied passages and around edits - are factored greedily against it: from the first window on, the longest
   factor that the block holds is taken; windows that cross a factor's end are looked up one by one, and what the block does not hold is added to it. Only factors
   of at least `window` words count; both a factor and its source in the block repeat.
3. Blocks of more than BLOCK differing stretches are compared by window hashes instead, which spread over all tasks.

The result is exact: it is that of comparing all windows (up to equal 64-bit hashes of different windows).

Defined results: null or empty texts have no words and lose none; texts shorter than a window lose nothing; repeated rows count as
documents of their own, so they remove each other; rows are told apart by 92 bits of hashes of id and text, so rows of one id, or without one, keep apart; extra columns
are ignored, clashing names included; an empty table gives an empty result.

Cost: about 7 % of word places are anchors; each task first folds its own equal stretches into one, and sends at most CROWD differing ones of a seed to its block to be counted, so a
passage or a seed that a third of all documents share sends a few rows per task, not per document. Whole texts move only where the table of places is too large for a broadcast.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilestar.llm import wordhash
from tilestar.runtime import Scratch

WINDOW, SEED_WORDS = 35, 8
#: Factor rows that a task folds at once; differing stretches of a seed in them that are sent to be counted; differing stretches of a block that one task parses.
FOLD_ROWS, CROWD, BLOCK = 1 << 20, 32, 4096
U = np.uint64
#: `place` packs: copied already (1 bit), hash of row (28), number of windows (5), first window (30).
_MULTI, _N, _START, _TAG = U(1 << 63), U(31 << 30), U((1 << 30) - 1), 35
FACTOR = "seed bigint, span bigint, doc bigint, place bigint, kind int"
PIECE = "seed bigint, doc bigint, place bigint, text binary"
#: kind: 0 a stretch to be compared, 1 a copy, 2 a stretch to be parsed
COMPARE, COPY, CHECK = 0, 1, 2


def _identity(doc: str, text: str) -> list[Column]:
    """(doc, tag): 64 and 28 bits that tell rows apart; rows equal in id and text are one."""
    own = [F.coalesce(F.col(doc).cast("bigint"), F.lit(-1)), F.col(text).cast("string")]
    tag = F.xxhash64(F.lit(5), *own, F.col(doc).isNull())
    return [F.xxhash64(F.lit(3), *own, F.col(doc).isNull()), F.shiftrightunsigned(tag, 36)]


def _batch(seed: np.ndarray, span: np.ndarray, doc: np.ndarray, place: np.ndarray, kind: int) -> pa.RecordBatch:
    as_long = lambda x: pa.array(np.ascontiguousarray(x).view(np.int64))
    return pa.RecordBatch.from_arrays([as_long(seed), as_long(span), as_long(doc), as_long(place), pa.array(np.full(len(seed), kind, np.int32))], names=["seed", "span", "doc", "place", "kind"])


def _copies(doc: np.ndarray, place: np.ndarray) -> pa.RecordBatch:
    """Copies travel by document, so that none of them meet at a hot seed."""
    return _batch(wordhash.mix(doc.view(U) ^ place), np.zeros(len(doc), U), doc, place, COPY)


def _fold(rows: np.ndarray, signed: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """rows: 4 x n (seed, span, doc, place). One row per (seed, span), in order (of signed numbers if asked), marked if it has copies; and the rows that are copies."""
    kind = np.int64 if signed else U
    rows = rows[:, np.lexsort((rows[1].view(kind), rows[0].view(kind)))]
    new = np.ones(rows.shape[1], bool)
    new[1:] = (rows[0, 1:] != rows[0, :-1]) | (rows[1, 1:] != rows[1, :-1])
    first = np.flatnonzero(new)
    size = np.diff(np.append(first, rows.shape[1]))
    multi = (size > 1) | (np.bitwise_or.reduceat(rows[3], first) & _MULTI != 0) if len(first) else np.zeros(0, bool)
    copies = rows[:, np.repeat(multi, size)]
    one = rows[:, first]
    one[3] = np.where(multi, one[3] | _MULTI, one[3])
    return one, copies


def _factors(data: bytes, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(seed, span, first window, number of windows) for each factor of a text."""
    _, _, h = wordhash.words(data)
    whole = wordhash.windows(h, window)
    if not len(whole):
        return (np.zeros(0, U),) * 4
    seeds = wordhash.windows(h, SEED_WORDS)
    anchor = wordhash.lowest(seeds, window - SEED_WORDS + 1)
    first = np.flatnonzero(np.concatenate(([True], anchor[1:] != anchor[:-1])))
    n = np.diff(np.append(first, len(anchor)))
    with np.errstate(over="ignore"):
        marks = wordhash.mix(whole + (anchor - np.arange(len(anchor))).astype(U) * wordhash.STEP)
        span = np.add.reduceat(marks, first)
    return seeds[anchor[first]], span, first.astype(U), n.astype(U)


def _emit(held: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    one, copies = _fold(np.concatenate(held, axis=1))
    if one.shape[1]:
        first = np.flatnonzero(np.concatenate(([True], one[0, 1:] != one[0, :-1])))
        size = np.diff(np.append(first, one.shape[1]))
        nth = np.arange(one.shape[1]) - np.repeat(first, size)
        # a crowd of differing stretches is known to differ; the first ones tell other tasks so
        known = np.repeat(size > CROWD, size) & (nth >= 2)
        if known.any():
            yield _batch(*one[:3, known], one[3, known] & ~_MULTI, CHECK)
        one = one[:, ~known]
    yield _batch(*one, COMPARE)
    if copies.shape[1]:
        yield _copies(copies[2], copies[3] & ~_MULTI)


def _folded(parts: Iterator[np.ndarray]) -> Iterator[pa.RecordBatch]:
    held, count = [], 0
    for part in parts:
        held.append(part)
        count += part.shape[1]
        if count >= FOLD_ROWS:
            yield from _emit(held)
            held, count = [], 0
    if held:
        yield from _emit(held)


def _doc_rows(doc: int, tag: int, seed: np.ndarray, span: np.ndarray, start: np.ndarray, n: np.ndarray) -> np.ndarray:
    place = (U(tag) << U(_TAG)) | (n << U(30)) | start
    return np.stack([seed, span, np.full(len(seed), doc, np.int64).view(U), place])


def _texts(batch: pa.RecordBatch) -> Iterator[tuple[int, int, bytes]]:
    ids, tags, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).cast(pa.binary())
    for i, tag, text in zip(ids, tags, texts, strict=True):
        yield i, tag, text.as_py() or b""


def _resolve(rows: DataFrame) -> DataFrame:
    """Compares stretches of equal seeds: copies, and stretches to be parsed. Rows stream through in order of (seed, span); no more than a batch is held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = np.zeros((4, 0), U)  # the folded stretch that may go on in the next batch
        told = False  # whether its seed had another one before

        def differing(rows: np.ndarray, check: np.ndarray) -> Iterator[pa.RecordBatch]:
            if check.any():
                yield _batch(*rows[:3, check], rows[3, check] & ~_MULTI, CHECK)

        for b in batches:
            kind = b.column(4).to_numpy()
            cols = np.stack([b.column(k).to_numpy().view(U) for k in range(4)])
            if (kind == COPY).any():
                yield _copies(cols[2, kind == COPY], cols[3, kind == COPY])
            yield from differing(cols, kind == CHECK)
            if not (kind == COMPARE).any():
                continue
            rows, copies = _fold(np.concatenate([last, cols[:, kind == COMPARE]], axis=1), signed=True)
            if copies.shape[1]:
                yield _copies(copies[2], copies[3] & ~_MULTI)
            same = rows[0, 1:] == rows[0, :-1]
            check = np.concatenate(([False], same)) | np.concatenate((same, [False])) | (told & (rows[0] == rows[0, 0]))
            yield from differing(rows[:, :-1], check[:-1])
            last, told = rows[:, -1:], bool(check[-1])
        yield from differing(last, np.full(last.shape[1], told))

    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    by = F.when(F.col("kind") == COMPARE, F.col("seed")).otherwise(F.xxhash64("doc", "place"))
    return rows.repartition(tasks, by).sortWithinPartitions("seed", "span").mapInArrow(run, FACTOR)


def _parsed(pieces: DataFrame, window: int) -> DataFrame:
    """Greedy factors of the pieces of each block: the copies among their windows. pieces: (seed, doc, place, text: the hashes of its windows)."""

    def parse(block: list[tuple[int, int, np.ndarray]]) -> list[tuple[int, int, int, int]]:
        """block: (doc, place without windows, first window, hashes). (doc, place, first window, number) of repeated windows."""
        index: dict[int, tuple[int, int]] = {}
        texts, found = [], []
        for own, (doc, place, first, text) in enumerate(block):
            texts.append(text)
            n, p = len(text), 0
            while p < n:
                source = index.get(text[p])
                if source is None:
                    index[text[p]] = (own, p)
                    p += 1
                    continue
                other, q = source
                there, f = texts[other], 1
                while p + f < n and q + f < len(there) and there[q + f] == text[p + f]:
                    f += 1
                found.append((doc, place, first + p, f))
                found.append((*block[other][:2], block[other][2] + q, f))
                p += f  # the next window crosses the factor's end
        return found

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seed, block, found = None, [], []

        def flush(found: list[tuple[int, int, int, int]]) -> pa.RecordBatch:
            doc, place, first, n = (np.array(x, U) for x in zip(*found, strict=True))
            return _copies(doc.view(np.int64), place | (n << U(30)) | first)

        mask = (1 << 63) - (1 << _TAG)
        for b in batches:
            for s, doc, place, text in zip(b.column(0).to_pylist(), b.column(1).to_numpy().view(U).tolist(), b.column(2).to_numpy().view(U).tolist(), b.column(3).to_pylist(), strict=True):
                if s != seed:
                    if len(block) > 1:
                        found += parse(block)
                    seed, block = s, []
                block.append((doc, place & mask, place & int(_START), np.frombuffer(text, U).tolist()))
            if found:
                yield flush(found)
                found = []
        if len(block) > 1:
            found += parse(block)
        if found:
            yield flush(found)

    tasks = int(pieces.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return pieces.repartition(tasks, "seed").sortWithinPartitions("seed").mapInArrow(run, FACTOR)


def repeated(df: DataFrame, scratch: Scratch, doc: str = "doc_id", text: str = "text", window: int = WINDOW) -> DataFrame:
    """(doc, tag, places): for each document with repeated windows, its places of repeated runs, packed as (windows << 30) + first window."""
    if not SEED_WORDS < window < SEED_WORDS + 31:
        raise ValueError("a factor holds at most 31 windows")
    key, tag = _identity(doc, text)
    docs = df.select(key.alias("doc"), tag.alias("tag"), F.col(text).cast("string").alias("text"))

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _folded(_doc_rows(i, tag, *_factors(t, window)) for b in batches for i, tag, t in _texts(b))

    def unpacked(places: pa.ListScalar) -> tuple[np.ndarray, np.ndarray]:
        p = np.unique(np.asarray(places.values).view(U))
        return (p & _START).astype(np.int64), ((p & _N) >> U(30)).astype(np.int64)

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Each stretch with the seed that all its windows share."""
        for b in batches:
            seeds, rows, texts = [], [], []
            for (i, tag, t), places in zip(_texts(b), b.column(3), strict=True):
                start, n = unpacked(places)
                h = wordhash.words(t)[2]
                eights, whole = wordhash.windows(h, SEED_WORDS), wordhash.windows(h, window)
                seeds.append(eights[start[:, None] + np.arange(window - SEED_WORDS + 1)].min(axis=1))
                rows.append(_doc_rows(i, tag, seeds[-1], seeds[-1], start.astype(U), n.astype(U)))
                texts += [whole[at : at + k].tobytes() for at, k in zip(start.tolist(), n.tolist(), strict=True)]
            if rows:
                r = np.concatenate(rows, axis=1)
                cols = [pa.array(np.ascontiguousarray(r[k]).view(np.int64)) for k in (0, 2, 3)]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(texts, pa.binary())], names=["seed", "doc", "place", "text"])

    def single(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Every window of the stretches by its own hash."""

        def parts() -> Iterator[np.ndarray]:
            for b in batches:
                for (i, tag, t), places in zip(_texts(b), b.column(3), strict=True):
                    start, n = unpacked(places)
                    at = np.unique(np.repeat(start, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n))
                    h = wordhash.windows(wordhash.words(t)[2], window)[at]
                    yield _doc_rows(i, tag, h, np.zeros(len(h), U), at.astype(U), np.ones(len(h), U))

        yield from _folded(parts())

    def by_doc(rows: DataFrame, *keys: str) -> DataFrame:
        tag = F.shiftrightunsigned(F.col("place").bitwiseAND(F.lit((1 << 63) - 1)), _TAG)
        return rows.groupBy("doc", tag.alias("tag"), *keys).agg(F.collect_set(F.col("place").bitwiseAND(F.lit((1 << _TAG) - 1))).alias("places"))

    first = scratch.save(_resolve(docs.mapInArrow(parse, FACTOR)), "first")
    check = first.filter(F.col("kind") == CHECK).select("seed", "doc", "place")
    large = scratch.save(check.groupBy("seed").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > BLOCK).select(F.col("seed").alias("large")), "large")
    flagged = check.join(scratch.small(large, "large"), F.col("seed") == F.col("large"), "left").withColumn("crowded", F.col("large").isNotNull())
    check = scratch.save(by_doc(flagged, "crowded"), "check")
    again = docs.join(scratch.small(check, "check"), ["doc", "tag"]).select("doc", "tag", "text", "places", "crowded")
    factors = _parsed(again.filter(~F.col("crowded")).select("doc", "tag", "text", "places").mapInArrow(pieces, PIECE), window)
    spread = _resolve(again.filter("crowded").select("doc", "tag", "text", "places").mapInArrow(single, FACTOR)).filter(F.col("kind") == COPY)
    found = scratch.save(by_doc(first.filter(F.col("kind") == COPY).unionByName(factors).unionByName(spread)), "found")
    scratch.drop("first", "check", "large")
    return found


def _stay(n: int, places: np.ndarray | None, window: int) -> np.ndarray:
    """Which of n words stay."""
    edge = np.zeros(n + 1, np.int64)
    if places is not None and len(places):
        p = places.view(U)
        start = (p & _START).astype(np.int64)
        np.add.at(edge, start, 1)
        np.add.at(edge, np.minimum(start + ((p & _N) >> U(30)).astype(np.int64) + window - 1, n), -1)
    return np.cumsum(edge)[:n] == 0


def cut(df: DataFrame, doc: str = "doc_id", text: str = "text", window: int = WINDOW, digest: bool = False) -> DataFrame:
    """df's columns with `text` cut to the words that stay, joined by one space; with digest, (doc, n_words, n_removed, kept_sha256) instead.

    In a text that loses nothing, white space stays as it is.
    """
    scratch = Scratch(df.sparkSession, "substring")
    found = scratch.small(repeated(df, scratch, doc, text, window), "found").select(F.col("doc").alias("__sub_doc"), F.col("tag").alias("__sub_tag"), F.col("places").alias("__sub_places"))
    key, tag = _identity(doc, text)
    same = (key == F.col("__sub_doc")) & (tag == F.col("__sub_tag"))
    base = df.select(F.col(doc), F.col(text)) if digest else df
    joined = base.join(found, same, "left").drop("__sub_doc", "__sub_tag")
    fields = [f for f in base.schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = b.schema.get_field_index(text)
            out, counts = [], []
            for t, places in zip(b.column(at).cast(pa.binary()), b.column(b.num_columns - 1), strict=True):
                data = t.as_py()
                hit = places.is_valid and len(places.values) > 0
                if not digest and not hit:
                    out.append(data)
                    continue
                own = (data or b"").split()
                stay = _stay(len(own), np.asarray(places.values) if hit else None, window)
                kept = b" ".join([w for w, s in zip(own, stay.tolist(), strict=True) if s] if hit else own)
                out.append(hashlib.sha256(kept).hexdigest() if digest else kept)
                counts.append((len(own), len(own) - int(stay.sum())))
            if digest:
                n, gone = (np.array(x, np.int64) for x in zip(*counts, strict=True)) if counts else (np.zeros(0, np.int64),) * 2
                yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(n), pa.array(gone), pa.array(out, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_sha256"])
            else:
                cols = [b.column(k) for k in range(b.num_columns - 1)]
                cols[at] = pa.array(out, pa.binary()).cast(pa.string())
                yield pa.RecordBatch.from_arrays(cols, names=[f.name for f in fields])

    return joined.mapInArrow(run, "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string" if digest else df.schema)


def op9_substring_dedup(df: DataFrame) -> DataFrame:
    return cut(df, digest=True)


SQL = r"""
WITH w AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
g AS (SELECT doc_id, i, array_to_string(ws[i:i + 34], ' ') AS win FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS i FROM w)),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY win) AS c FROM g) WHERE c > 1),
c AS (SELECT doc_id, list(DISTINCT i + j) AS gone FROM r, range(0, 35) t(j) GROUP BY doc_id),
k AS (SELECT w.doc_id, len(ws) AS n, coalesce(len(gone), 0) AS m,
             CASE WHEN gone IS NULL THEN array_to_string(ws, ' ') ELSE
               coalesce((SELECT string_agg(ws[p], ' ' ORDER BY p) FROM (SELECT unnest(range(1, len(ws) + 1)) AS p) q WHERE NOT list_contains(gone, p)), '') END AS kept
      FROM w LEFT JOIN c USING (doc_id))
SELECT doc_id, n::BIGINT AS n_words, m::BIGINT AS n_removed, sha256(kept) AS kept_sha256 FROM k
"""
