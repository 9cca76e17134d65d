"""Byte-level BPE by speculation: propose tokens, verify them, merge exactly only where that fails.

Each distinct word of a batch is cut greedily into the longest tokens that match. A token sequence is the BPE encoding of its bytes if and only if
every token encodes to itself and every adjacent pair encodes to that pair, so all adjacent pairs of a batch are checked at once against a
table of known pairs; pairs not met before are settled by merging just their bytes. Words with a failing pair are merged exactly.

Defined results: null text counts as empty and has no tokens; a special token's string in a text is that token, as the tokenizers library has it;
very long texts and words without white space take time in proportion to n log n; repeated rows are encoded alike; extra columns are ignored; an
empty table gives an empty result. The tokenizer's file is a parameter and must be a byte-level BPE without normaliser, with the standard pre-tokeniser.
The file is read on the driver; its tables, bounded by the vocabulary, are broadcast, and a worker keeps them and the words it has met from task to task.

Memory: the word table is emptied at `WORDS` entries; a batch's own words come on top.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilestar.runtime import kept_in_workers

#: Fixed value: the pre-tokeniser's pattern, as public_tokenizers.PATTERN states it.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
WORDS = 700_000
#: Words of more bytes than this are merged with a heap.
SHORT = 48


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _byte_of() -> dict[str, int]:
    """Printable stand-ins of byte-level BPE: printable Latin-1 characters for themselves, then 256 and up for the rest, in order."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


class Codec:
    """Encoder and decoder of one tokenizer file."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, at = spec["model"], _byte_of()
        if spec["normalizer"] or model["type"] != "BPE" or spec["pre_tokenizer"]["type"] != "ByteLevel" or spec["pre_tokenizer"]["add_prefix_space"]:
            raise ValueError("not a plain byte-level BPE")
        raw = {token: bytes(at[c] for c in token) for token in model["vocab"]}
        self.id_of = {raw[token]: k for token, k in model["vocab"].items()}
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.bytes_of = dict.fromkeys(range(max([*model["vocab"].values(), *self.special.values()]) + 1), b"")
        self.bytes_of |= {k: b for b, k in self.id_of.items()} | {k: s.encode() for s, k in self.special.items()}
        self.base = [self.id_of[bytes([b])] for b in range(256)]
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        self.rank_of: dict[int, int] = {}  # a << 24 | b: rank
        self.made: list[int] = []
        for rank, pair in enumerate(model["merges"]):
            a, b = (raw[x] for x in (pair if isinstance(pair, list) else pair.split(" ")))
            self.merges[self.id_of[a], self.id_of[b]] = (rank, self.id_of[a + b])
            self.rank_of[self.id_of[a] << 24 | self.id_of[b]] = rank
            self.made.append(self.id_of[a + b])
        self.longest = max(map(len, self.id_of))
        self.split = regex.compile(PATTERN).findall
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")").split if self.special else None
        self.size = len(self.bytes_of)
        self.known = np.zeros(0, np.int64)  # pairs settled so far, sorted
        self.valid = np.zeros(0, bool)
        self.exact_words = 0
        self._clear()

    def _clear(self) -> None:
        self.place: dict[str, int] = {}
        self.flat, self.start, self.length = np.zeros(0, np.uint32), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def merge(self, word: bytes) -> list[int]:
        """BPE by its definition: always the pair of lowest rank, leftmost first. Short words by lists, others by a heap over a linked list."""
        ids = [self.base[b] for b in word]
        n = len(ids)
        if n < 2:
            return ids
        if n <= SHORT:
            get, made, none = self.rank_of.get, self.made, len(self.made)
            ranks = [get(a << 24 | b, none) for a, b in zip(ids, ids[1:], strict=False)]
            while ranks and (low := min(ranks)) < none:
                i = ranks.index(low)
                ids[i] = one = made[low]
                del ids[i + 1], ranks[i]
                if i:
                    ranks[i - 1] = get(ids[i - 1] << 24 | one, none)
                if i < len(ranks):
                    ranks[i] = get(one << 24 | ids[i + 1], none)
            return ids
        left, right, alive = list(range(-1, n - 1)), [*range(1, n), -1], [True] * n
        get = self.merges.get
        heap = [(m[0], i, ids[i], ids[i + 1], m[1]) for i in range(n - 1) if (m := get((ids[i], ids[i + 1])))]
        heapq.heapify(heap)
        while heap:
            _, i, a, b, made = heapq.heappop(heap)
            j = right[i] if alive[i] else -1
            if j < 0 or ids[i] != a or ids[j] != b:
                continue
            ids[i], alive[j] = made, False
            right[i] = k = right[j]
            if k >= 0:
                left[k] = i
                if m := get((made, ids[k])):
                    heapq.heappush(heap, (m[0], i, made, ids[k], m[1]))
            if (h := left[i]) >= 0 and (m := get((ids[h], made))):
                heapq.heappush(heap, (m[0], h, ids[h], made, m[1]))
        return [x for x, ok in zip(ids, alive, strict=True) if ok]

    def propose(self, word: bytes) -> list[int]:
        """Greedy longest match."""
        out, i, n, get, most = [], 0, len(word), self.id_of.get, self.longest
        if (whole := get(word)) is not None:
            return [whole]
        while i < n:
            j = min(n, i + most)
            while (k := get(word[i:j])) is None:
                j -= 1
            out.append(k)
            i = j
        return out

    def _compatible(self, pairs: np.ndarray) -> np.ndarray:
        """Whether each pair code a * (size + 1) + b encodes to itself; b = size stands for no second token."""
        distinct, back = np.unique(pairs, return_inverse=True)
        new = np.setdiff1d(distinct, self.known, assume_unique=True)
        if len(new):
            a, b = new // (self.size + 1), new % (self.size + 1)
            good = np.fromiter((self.merge(self.bytes_of[x] + (self.bytes_of[y] if y < self.size else b"")) == ([x, y] if y < self.size else [x]) for x, y in zip(a.tolist(), b.tolist(), strict=True)), bool, len(new))
            known, valid = np.concatenate((self.known, new)), np.concatenate((self.valid, good))
            order = np.argsort(known)
            self.known, self.valid = known[order], valid[order]
        return self.valid[np.searchsorted(self.known, distinct)][back]

    def _learn(self, words: list[str]) -> None:
        """Adds words to the table."""
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        guess = [self.propose(w) for w in raw]
        size = np.fromiter(map(len, guess), np.int64, len(guess))
        flat = np.fromiter((x for g in guess for x in g), np.int64, int(size.sum()))
        last = np.cumsum(size) - 1
        second = np.append(flat[1:], 0)
        second[last] = self.size  # a word's last token is checked by itself
        good = np.logical_and.reduceat(self._compatible(flat * (self.size + 1) + second), np.cumsum(size) - size)
        for k in np.flatnonzero(~good).tolist():
            guess[k] = self.merge(raw[k])
            self.exact_words += 1
        size = np.fromiter(map(len, guess), np.int64, len(guess))
        flat = np.fromiter((x for g in guess for x in g), np.uint32, int(size.sum()))
        n = len(self.place)
        self.place.update(zip(words, range(n, n + len(words)), strict=True))
        self.start = np.concatenate((self.start, len(self.flat) + np.cumsum(size) - size))
        self.length = np.concatenate((self.length, size))
        self.flat = np.concatenate((self.flat, flat))

    def encode(self, texts: Iterable[str | None]) -> Iterator[np.ndarray]:
        """Token ids of each text, as uint32."""
        batch: list[list[list[str] | int]] = []
        held = 0
        for text in texts:
            parts = self.cut(text or "") if self.cut else [text or ""]
            batch.append([self.special[p] if k % 2 else self.split(p) for k, p in enumerate(parts)])
            held += sum(len(p) for p in batch[-1] if isinstance(p, list))
            if held > 500_000:
                yield from self._flush(batch)
                batch, held = [], 0
        yield from self._flush(batch)

    def _flush(self, batch: list[list[list[str] | int]]) -> Iterator[np.ndarray]:
        if len(self.place) > WORDS:
            self._clear()
        fresh = {w for doc in batch for part in doc if isinstance(part, list) for w in part} - self.place.keys()
        if fresh:
            self._learn(list(fresh))
        for doc in batch:
            out = [np.array([part], np.uint32) if isinstance(part, int) else self._ids(part) for part in doc]
            yield out[0] if len(out) == 1 else np.concatenate(out)

    def _ids(self, words: list[str]) -> np.ndarray:
        at = np.fromiter(map(self.place.__getitem__, words), np.int64, len(words))
        n = self.length[at]
        return self.flat[np.repeat(self.start[at] - (np.cumsum(n) - n), n) + np.arange(n.sum())]

    def decode(self, ids: np.ndarray) -> bytes:
        """UTF-8 of the decoded text; what is not valid becomes the replacement character."""
        raw = b"".join(map(self.bytes_of.__getitem__, ids.tolist()))
        return raw.decode("utf-8", "replace").encode("utf-8")


def encode(df: DataFrame, path: str, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, ids array<int>) for every row."""

    shared = kept_in_workers(df.sparkSession, Codec(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = shared()
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.view(np.int32) for x in codec.encode(b.column(1).to_pylist())], pa.list_(pa.int32()))], names=["id", "ids"])

    return df.select(F.col(id_col).cast("bigint").alias("id"), F.col(text).cast("string").alias("text")).mapInArrow(run, "id bigint, ids array<int>")


def decode(df: DataFrame, path: str, id_col: str = "id", ids: str = "ids") -> DataFrame:
    """(id, text) from token ids; null ids count as none."""

    shared = kept_in_workers(df.sparkSession, Codec(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = shared()
        for b in batches:
            texts = [codec.decode(np.asarray(x or [], np.uint32)).decode() for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], names=["id", "text"])

    return df.select(F.col(id_col).cast("bigint").alias("id"), F.col(ids).cast("array<int>").alias("ids")).mapInArrow(run, "id bigint, text string")


def op5_bpe(df: DataFrame, path: str | None = None) -> DataFrame:
    path = path or default_path()

    shared = kept_in_workers(df.sparkSession, Codec(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = shared()
        for b in batches:
            n, coded, decoded = [], [], []
            for ids in codec.encode(b.column(1).to_pylist()):
                n.append(len(ids))
                coded.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                decoded.append(hashlib.sha256(codec.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(coded, pa.string()), pa.array(decoded, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return df.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
