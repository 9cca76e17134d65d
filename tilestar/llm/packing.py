"""Packing of token sequences by a configuration linear program over the length histogram.

Documents are tokenised and closed with an end token; those over the capacity are cut into full pieces, the remainder first. What matters
of the pieces is the histogram of their lengths, at most `capacity` numbers, whatever the size of the corpus. Over it the configuration program (fill
each length's demand with as few sequences, each a multiset of lengths within the capacity) is relaxed and solved by multiplicative weights: lengths have prices, a
knapsack dynamic program finds the dearest configuration, it is used, and the prices of its lengths fall exponentially with how often they are covered. The prices also
prove a lower bound on the number of sequences. Amounts are rounded down, what is left is relaxed again while that helps, and the last pieces are placed by fullest sequences, best fit or search,
whichever needs least. `solve` returns the bound with the plan.

Pieces then get their places by rank within their length; ranks come from counts per length and bucket, so no length is gathered in one task.

Defined results: null text counts as empty and packs as the end token alone; repeated rows are packed each; rows with equal id and piece are
told apart by their tokens where these differ, and are interchangeable where not; extra columns are ignored; an empty table gives an empty result.

Token ids: the vocabulary as ranks is encoded by tiktoken, which gives the ids of the tokenizers library; texts it refuses (runs of white space
too long for its matcher) go through the exact codec of bpe.py.
"""

from __future__ import annotations

import base64
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tilestar.llm import bpe
from tilestar.runtime import Scratch, kept_in_workers

#: Fixed values of the contract.
CAPACITY, END = 1024, 2
#: Rounding by fullest sequences: share of a configuration's scarcest length that one step places; decay of a price with the share placed; weight of that beside the room used;
#: share of each length left to best fit; knapsack calls.
SHARE, ETA, TILT, REST, CALLS = 0.5, 4.0, 1e-2, 0.2, 200
#: Relaxed program: knapsack calls times lengths; gap of its amounts to the proven bound that ends it; gap of a whole packing to the bound that needs no better one.
WORK, TOLERANCE, NEAR = 60_000, 1e-4, 5e-4
#: Search for the last pieces: so many pieces at most, nodes, ways to complete a sequence.
FEW, NODES, WAYS = 60, 1000, 100
PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint"


class Ids:
    """Text to token ids. Encoders are built where they are first used, and kept while the worker lives."""

    def __init__(self, ranks: str, exact: str) -> None:
        with open(ranks, "rb") as f:
            self.ranks = f.read()
        self.codec, self.fast = bpe.Codec(exact), None

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is None:
            import tiktoken

            table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, self.ranks.splitlines())}
            self.fast = tiktoken.Encoding("ranks", pat_str=bpe.PATTERN, mergeable_ranks=table, special_tokens=self.codec.special)
        try:
            return self.fast.encode_to_numpy(text, allowed_special="all")
        except ValueError:
            return next(self.codec.encode([text]))


def cuts(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: full ones, preceded by the remainder."""
    first = n % capacity or min(n, capacity)
    return [(0, first), *((at, capacity) for at in range(first, n, capacity))]


def pieces(df: DataFrame, ranks: str, exact: str, capacity: int = CAPACITY, end: int = END, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32."""

    shared = kept_in_workers(df.sparkSession, Ids(ranks, exact))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids_of = shared()
        for b in batches:
            rows = []
            for doc, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = np.append(ids_of(t.as_py() or ""), np.uint32(end)).astype("<u4")
                rows += [(doc, k, at, n, zlib.crc32(ids[at : at + n].tobytes())) for k, (at, n) in enumerate(cuts(len(ids), capacity))]
            cols = list(zip(*rows, strict=True)) or [[]] * 5
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return df.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(run, PIECES)


def dearest(price: np.ndarray, lengths: np.ndarray, most: np.ndarray, capacity: int) -> Counter:
    """Knapsack by dynamic programming: the multiset of lengths, of each at most `most`, of the greatest price within the capacity."""
    items = []  # a length so many times, in powers of two
    for n, p, k in zip(lengths.tolist(), price.tolist(), np.minimum(most, capacity // lengths).tolist(), strict=True):
        times = 1
        while k:
            times = min(times, k)
            items.append((n, times, p))
            k, times = k - times, 2 * times
    best, took = np.zeros(capacity + 1), np.zeros((len(items), capacity + 1), bool)
    for row, (n, times, p) in enumerate(items):
        w = n * times
        offer = best[:-w] + p * times
        np.greater(offer, best[w:], out=took[row, w:])
        np.maximum(offer, best[w:], out=best[w:])
    out, room = Counter(), capacity
    for row in range(len(items) - 1, -1, -1):
        if took[row, room]:
            n, times, _ = items[row]
            out[n] += times
            room -= n * times
    return out


def dearest_free(price: np.ndarray, lengths: np.ndarray, capacity: int) -> Counter:
    """As `dearest`, each length as often as it fits; one step a unit of capacity, which is less work where lengths are many. lengths: ascending."""
    best, took = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    fits = np.searchsorted(lengths, np.arange(capacity + 1), side="right").tolist()
    for room in range(int(lengths[0]), capacity + 1):
        offer = best[room - lengths[: fits[room]]] + price[: fits[room]]
        k = int(offer.argmax())
        best[room], took[room] = (offer[k], k) if offer[k] > best[room - 1] else (best[room - 1], -1)
    out, room = Counter(), capacity
    while room > 0:
        if took[room] < 0:
            room -= 1
        else:
            out[int(lengths[took[room]])] += 1
            room -= int(lengths[took[room]])
    return out


def _best_fit(left: np.ndarray, capacity: int) -> list[tuple[Counter, int]]:
    """Best-fit decreasing on a histogram; sequences of equal contents are one group."""
    rooms: dict[int, list[tuple[Counter, int]]] = {}
    for n in np.flatnonzero(left)[::-1].tolist():
        count = int(left[n])
        while count:
            room = min((r for r, g in rooms.items() if r >= n and g), default=None)
            if room is None:
                each = min(capacity // n, count)
                many = count // each
                rooms.setdefault(capacity - each * n, []).append((Counter({n: each}), many))
                count -= each * many
                continue
            held, many = rooms[room].pop()
            each = min(room // n, max(1, count // many))
            use = min(many, count // each) or 1
            if use < many:
                rooms[room].append((held, many - use))
            rooms.setdefault(room - each * n, []).append((held + Counter({n: each}), use))
            count -= each * use
    return [g for groups in rooms.values() for g in groups]


def _key(config: Counter) -> tuple[tuple[int, int], ...]:
    return tuple(sorted(config.items()))


def _used(configs: list[tuple[Counter, int]]) -> int:
    return sum(many for _, many in configs)


@dataclass
class Relaxed:
    """The configuration program without whole numbers: configurations with their amounts, and the greatest lower bound that its prices proved."""

    amounts: dict[tuple[tuple[int, int], ...], float]
    bound: float


def relax(demand: np.ndarray, capacity: int = CAPACITY, work: int = WORK) -> Relaxed:
    """Multiplicative weights over all lengths of demand[n].

    A length's price starts at its share of the capacity, or at that of the sequences that hold nothing else, or alike, or only long ones have one: whichever proves most. The dearest configuration is used until its scarcest length is covered by a step more; a price falls
    exponentially with how often its length is covered. Steps are halved turn by turn, and the amounts are those of the last turn that covered every length. Any
    prices prove a lower bound: the price of all pieces over that of the dearest configuration.
    """
    lengths = np.flatnonzero(demand)
    want = demand[lengths].astype(float)
    most, many = np.full(len(lengths), capacity), np.log2(capacity / lengths + 1).sum() > capacity / 2
    covered, logs = np.zeros(len(lengths)), np.zeros(len(lengths))
    amounts, kept, step, calls = {}, {}, 0.5, max(200, work // max(len(lengths), 1))
    index = {n: k for k, n in enumerate(lengths.tolist())}

    def priced(price: np.ndarray) -> tuple[Counter, np.ndarray, np.ndarray, float]:
        """The dearest configuration, its lengths and their numbers, and the bound that the prices prove."""
        config = dearest_free(price, lengths, capacity) if many else dearest(price, lengths, most, capacity)
        at, each = np.array([index[n] for n in config]), np.array(list(config.values()), float)
        return config, at, each, float(price @ want) / float(price[at] @ each)

    priors = [lengths / capacity, 1 / (capacity // lengths), np.ones(len(lengths)), (2 * lengths > capacity) + 1e-6]
    proofs = [priced(p)[-1] for p in priors]
    prior, best = priors[int(np.argmax(proofs))], max(proofs)
    for _ in range(calls):
        price = prior * np.exp(np.clip(logs - logs.max(), -60, 0))
        config, at, each, proved = priced(price)
        best = max(best, proved)
        use = float((want[at] / each).min()) * step
        amounts[_key(config)] = amounts.get(_key(config), 0.0) + use
        gain = use * each / want[at]
        covered[at] += gain
        logs[at] -= gain
        if covered.min() >= 1:
            total = sum(amounts.values()) / covered.min()
            kept = {c: x / covered.min() for c, x in amounts.items()}
            if total <= best * (1 + TOLERANCE):
                break
            if covered.min() >= 3:  # a turn ends: prices stay, amounts begin anew with smaller steps
                covered, amounts, step = np.zeros(len(lengths)), {}, max(step / 2, 1e-3)
    if not kept:
        kept = {c: x / max(float(covered.max()), 1.0) for c, x in amounts.items()}
    return Relaxed(kept, best)


def _completed(left: np.ndarray, capacity: int, bound: int, most: int) -> list[tuple[Counter, int]] | None:
    """A packing of few pieces in fewer than `most` sequences, by search: the largest piece left is completed in all ways, fullest first. None if NODES did not find one."""
    pieces = Counter({n: int(left[n]) for n in np.flatnonzero(left).tolist()})
    best: list[Counter] | None = None
    limit, nodes = most, 0

    def ways(room: int, sizes: list[int], rest: Counter) -> Iterator[Counter]:
        if not sizes or room < sizes[-1]:
            yield Counter()
            return
        n = sizes[0]
        for k in range(min(rest[n], room // n), -1, -1):
            for more in ways(room - k * n, sizes[1:], rest):
                yield more + Counter({n: k}) if k else more

    def search(rest: Counter, done: list[Counter]) -> None:
        nonlocal best, limit, nodes
        nodes += 1
        volume = sum(n * k for n, k in rest.items())
        if not volume:
            best, limit = list(done), len(done)
            return
        if nodes > NODES or len(done) + -(-volume // capacity) >= limit:
            return
        first = max(n for n, k in rest.items() if k)
        own = rest - Counter({first: 1})
        found = list(islice(ways(capacity - first, sorted((n for n, k in own.items() if k), reverse=True), own), WAYS))
        for way in sorted(found, key=lambda w: -sum(n * k for n, k in w.items())):
            search(own - way, [*done, way + Counter({first: 1})])
            if limit <= bound or nodes > NODES:
                return

    search(pieces, [])
    return [(c, 1) for c in best] if best is not None else None


def _filled(left: np.ndarray, capacity: int, share: float, calls: int) -> list[tuple[Counter, int]]:
    """Rounding by fullest sequences: the configuration that fills most, of equal ones that of the lengths with most left, for a share of its scarcest length; then best fit."""
    left, out = left.copy(), []
    want = np.maximum(left, 1)
    for _ in range(calls):
        lengths = np.flatnonzero(left > REST * want)
        if not len(lengths):
            break
        weight = lengths / capacity * np.exp(-ETA * (1 - left[lengths] / want[lengths]))
        config = dearest(lengths * (1 + TILT * weight), lengths, left[lengths], capacity)
        use = max(1, int(share * min(int(left[n]) // k for n, k in config.items())))
        for n, k in config.items():
            left[n] -= k * use
        out.append((config, use))
    return out + _best_fit(left, capacity)


def _rounded(left: np.ndarray, relaxed: Relaxed, capacity: int) -> tuple[list[tuple[Counter, int]], np.ndarray]:
    """Amounts rounded down, the greatest first, as far as pieces are left; and what is left."""
    left, out = left.copy(), []
    for config, amount in sorted(relaxed.amounts.items(), key=lambda x: (-x[1], x[0])):
        use = min(int(amount + 1e-9), *(int(left[n]) // k for n, k in config))
        if use:
            for n, k in config:
                left[n] -= k * use
            out.append((Counter(dict(config)), use))
    return out, left


def _tail(left: np.ndarray, capacity: int, calls: int) -> list[tuple[Counter, int]]:
    """The best rounding of what no whole amount holds."""
    if not left.any():
        return []
    tries = [_best_fit(left, capacity), _filled(left, capacity, SHARE, calls)]
    best = min(tries, key=_used)
    least = -(-int((np.arange(capacity + 1) * left).sum()) // capacity)
    if int(left.sum()) <= FEW and _used(best) > least:
        best = _completed(left, capacity, least, _used(best)) or best
    return best


def solve(histogram: np.ndarray, capacity: int = CAPACITY) -> tuple[list[tuple[Counter, int]], int]:
    """(configuration, number of sequences) that hold each piece exactly once, and a proven lower bound of the number of sequences.

    The program is relaxed and rounded; what is left is relaxed again while that helps, until the packing comes within NEAR of the bound, rounded up to whole sequences. If it does
    not, rounding alone is tried on all pieces too, and the least counts.
    """
    left = histogram.astype(np.int64).copy()
    alone = [(Counter({capacity: 1}), int(left[capacity]))] if left[capacity] else []
    left[capacity] = 0
    if not left.any():
        return alone, _used(alone)
    relaxed = relax(left, capacity)
    least = max(-(-int((np.arange(capacity + 1) * left).sum()) // capacity), int(np.ceil(relaxed.bound - 1e-6)))
    enough = int(np.ceil(least * (1 + NEAR)))
    held, after = _rounded(left, relaxed, capacity)
    best = held + _tail(after, capacity, CALLS // 4)
    while _used(best) > enough and after.any():
        more, after = _rounded(after, relax(after, capacity, WORK // 4), capacity)
        held = held + more
        tried = held + _tail(after, capacity, CALLS // 4)
        better = _used(tried) < _used(best)
        best = min(best, tried, key=_used)
        if not better or not more:
            break
    if _used(best) > enough:
        best = min(best, _tail(left, capacity, CALLS), key=_used)
    return alone + best, least + _used(alone)


def plan(histogram: np.ndarray, capacity: int = CAPACITY) -> list[tuple[Counter, int]]:
    """histogram[n]: pieces of length n. (configuration, number of sequences) that hold each piece exactly once."""
    return solve(histogram, capacity)[0]


def places(configs: list[tuple[Counter, int]]) -> dict[str, np.ndarray]:
    """For runs of ranks of a length: length, first rank, pieces per sequence, first sequence, offset of the first piece. Sorted."""
    rows, rank, sequence = [], Counter(), 0
    for config, many in configs:
        offset = 0
        for n, k in sorted(config.items(), reverse=True):
            rows.append((n, rank[n], k, sequence, offset))
            rank[n] += k * many
            offset += k * n
        sequence += many
    rows.sort()
    names = ("length", "rank", "each", "sequence", "offset")
    return dict(zip(names, np.array(rows, np.int64).reshape(-1, 5).T, strict=True))


def pack(df: DataFrame, ranks: str | None = None, exact: str | None = None, capacity: int = CAPACITY, end: int = END, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Every piece with its sequence_id and offset."""
    if ranks is None or exact is None:
        import public_tokenizers

        ranks, exact = ranks or public_tokenizers.path("byte_bpe_50k.tiktoken"), exact or bpe.default_path()
    spark = df.sparkSession
    scratch = Scratch(spark, "packing")
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    cut = scratch.save(pieces(df, ranks, exact, capacity, end, id_col, text).withColumn("bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)).cast("int")), "pieces")
    counts = scratch.save(cut.groupBy("length", "bucket").agg(F.count("*").alias("n")), "counts")
    histogram = np.zeros(capacity + 1, np.int64)
    for n, count in counts.groupBy("length").agg(F.sum("n")).collect():  # at most `capacity` rows
        histogram[n] = count
    table = places(plan(histogram, capacity))
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("length", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    own = Window.partitionBy("length", "bucket").orderBy("doc_id", "piece", "start", "ids_crc32")
    ranked = cut.withColumn("own", F.row_number().over(own)).join(offsets, ["length", "bucket"]).withColumn("rank", F.col("before") + F.col("own") - 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key = (table["length"] << 48) | table["rank"]
        for b in batches:
            length, rank = (b.column(k).to_numpy() for k in (3, 5))
            k = np.searchsorted(key, (length << 48) | rank, side="right") - 1
            nth = rank - table["rank"][k]
            sequence, offset = table["sequence"][k] + nth // table["each"][k], table["offset"][k] + nth % table["each"][k] * length
            yield pa.RecordBatch.from_arrays([b.column(i) for i in range(5)] + [pa.array(sequence), pa.array(offset)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank").mapInArrow(run, PIECES + ", sequence_id bigint, offset bigint")


def op8_packing(df: DataFrame) -> DataFrame:
    return pack(df)
