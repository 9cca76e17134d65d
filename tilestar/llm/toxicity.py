"""Toxicity scores from a subsequence string kernel, Nyström landmarks and a linear support vector machine.

Kernel: two strings are compared by their common subsequences of three characters that span at most `SPAN` characters, each weighted by
DECAY to the power of its span in either string, so insults with gaps or inserted characters stay close to the plain ones. It is scaled by length.
Units are lower-cased words, and runs of single-character words joined ("i d i o t"). A sentence scores as its most offensive unit: the kernel of two sentences is that of
the units that stand for them.

Training, on labelled sentences: the sentences of the labelled documents have the label of their document, and which unit stands for a sentence is learned with the machine.
It begins with the unit whose share of toxic documents lies most standard errors above its share of clean ones; in later rounds it is the unit of the greatest margin. A
document gives its sentences of positive margin, a clean one also its worst sentences and, so that ordinary units are known too, some drawn by hash. The kernel to landmark units,
whitened (Nyström), feeds a linear squared-hinge SVM in the primal. As the kernel is an inner
product of subsequence weights, the trained machine folds into one weight per three-character subsequence, so a unit costs a few table reads.
A logistic model over a document's unit margins, fitted on training documents, turns margins into a score of 0 to 1.

Only rows of the training part are read for labels: those whose crc32(doc_id as text) mod 4 is not 2. At most TRAIN_DOCS labelled documents, those of the smallest
hash of their id, are used to fit; all documents are scored on their whole texts.

Defined results: null and empty texts get the score of a text without any word; repeated rows get equal scores; labels that are null are not used, of
several labels of a document the highest counts; without both classes in training every score is the share of toxic labels (0 if there are none);
extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tilestar.runtime import Scratch, kept_in_workers

#: Bound of the training sample, in documents; landmarks.
TRAIN_DOCS, LANDMARKS = 20_000, 256
#: Sentences that a document gives at most; worst ones and drawn units that a clean one gives in any case; rate at which a unit counts as clean; rounds.
SENTENCES, WORST, DRAWN, SHARED, ROUNDS = 12, 3, 6, 0.25, 3
SPAN, DECAY, RIDGE = 6, 0.6, 0.05
#: Longest unit; longer words are read in overlapping stretches.
REACH = 24
#: Symbols of the kernel: letters and digits that stand for them have their own, other code points share the rest by remainder, so that the letters of one script stay apart.
SYMBOLS = 64
_SPACE = re.compile("[ \t\n\x0b\x0c\r]+")
_SENTENCE = re.compile("[.!?]+[ \t\x0b\x0c\r]+|\n+")
#: Marks the ends of a word; what is taken off its ends before.
EDGE, TRIM = "\x01", ".,;:!?\"'()[]{}*#%&$|<>-_"
THRESHOLD = 0.3
#: Digits and signs that stand for letters.
STANDS_FOR = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a"}
#: Places of the three characters, relative to the first.
OFFSETS = [(a, b) for a, b in combinations(range(1, SPAN), 2)]


def _symbol_table() -> np.ndarray:
    """Code point to symbol, for code points below 1024; 0 is no character."""
    table = np.array([28 + cp % (SYMBOLS - 28) for cp in range(1024)], np.int64)
    table[ord(EDGE)] = 27
    table[97:123] = np.arange(1, 27)
    for sign, letter in STANDS_FOR.items():
        table[ord(sign)] = ord(letter) - 96
    table[0] = 0
    return table


_SYMBOL = _symbol_table()


def units(text: str | None) -> tuple[set[str], int]:
    """Distinct units of a text, and its number of words."""
    words = [w for w in _SPACE.split((text or "").lower()) if w]
    out = {w.strip(TRIM) for w in set(words)}
    out.discard("")
    run: list[str] = []
    for w in [*words, "  "]:
        if len(w) == 1 and w.isalpha():
            run.append(w)
        else:
            if len(run) > 2:
                out.add("".join(run))
            run = []
    long = [w for w in out if len(w) > REACH - 2]
    for w in long:
        out.discard(w)
        out.update(w[k : k + REACH - 2] for k in range(0, len(w) - 8, REACH - 10))
    return out, len(words)


def sentences(text: str | None) -> list[list[str]]:
    """The units of each sentence that has any, in order of their code points."""
    return [sorted(own) for part in _SENTENCE.split(text or "") if (own := {u for u in units(part)[0] if len(u) > 2})]


def _codes(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Symbols (n x REACH + SPAN - 1) and lengths."""
    raw = np.array([f"{EDGE}{w}{EDGE}" for w in words], f"<U{REACH}").view(np.uint32).reshape(len(words), REACH)
    sym = np.where(raw < 1024, _SYMBOL[np.minimum(raw, 1023)], 28 + raw % (SYMBOLS - 28))
    return np.pad(sym, ((0, 0), (0, SPAN - 1))), np.count_nonzero(raw, axis=1)


def _scale(length: np.ndarray) -> np.ndarray:
    """Kernel of a string with itself if no subsequence repeats."""
    total = np.zeros(len(length))
    for _, b in OFFSETS:
        total += np.maximum(length - b, 0) * DECAY ** (2 * (b + 1))
    return np.sqrt(np.maximum(total, DECAY**6))


def _triples(sym: np.ndarray) -> Iterator[tuple[np.ndarray, float]]:
    """For each pair of offsets: codes of the subsequences that start at each place, -1 beyond the end; their weight."""
    for a, b in OFFSETS:
        c0, c1, c2 = sym[:, :REACH], sym[:, a : a + REACH], sym[:, b : b + REACH]
        yield np.where(c2 > 0, (c0 * SYMBOLS + c1) * SYMBOLS + c2, -1), DECAY ** (b + 1)


def kernel(words: list[str], landmarks: list[str]) -> np.ndarray:
    """Kernel matrix, words x landmarks."""
    sym, length = _codes(landmarks)
    coded = [(code.ravel(), weight) for code, weight in _triples(sym)]
    column = np.zeros(SYMBOLS**3 + 1, np.int32)
    own = np.unique(np.concatenate([c for c, _ in coded]))
    own = own[own >= 0]
    column[own] = np.arange(1, len(own) + 1)  # row 0 is for subsequences of no landmark
    weights = np.zeros((len(own) + 1, len(landmarks)), np.float32)
    rows = np.repeat(np.arange(len(landmarks)), REACH)
    for code, weight in coded:
        np.add.at(weights, (column[code], rows), weight)
    weights[0] = 0
    weights /= _scale(length)
    sym, length = _codes(words)
    out = np.zeros((len(words), len(landmarks)), np.float32)
    for code, weight in _triples(sym):
        at = column[code]
        for place in range(REACH):
            used = np.flatnonzero(at[:, place])
            out[used] += weight * weights[at[used, place]]
    return out / _scale(length)[:, None]


class Machine:
    """Margins of words: one weight for each subsequence, and a bias; then a logistic model over documents."""

    def __init__(self, table: np.ndarray, bias: float) -> None:
        self.table, self.bias = table, bias
        self.center, self.spread, self.coef = np.zeros(4), np.ones(4), np.zeros(5)

    def margins(self, words: list[str]) -> np.ndarray:
        sym, length = _codes(words)
        total = np.zeros(len(words), np.float32)
        for code, weight in _triples(sym):
            total += weight * self.table[code].sum(axis=1)
        return total / _scale(length) + self.bias

    def document(self, texts: list[str | None]) -> np.ndarray:
        """Document features: highest margin, sum of positive margins, words over the margin, and their share."""
        sets = [units(t) for t in texts]
        every = list(set().union(*(s for s, _ in sets))) if sets else []
        value = dict(zip(every, self.margins(every).tolist(), strict=True)) if every else {}
        out = np.zeros((len(texts), 4))
        for k, (own, n) in enumerate(sets):
            m = np.fromiter((value[w] for w in own), np.float64, len(own)) if own else np.full(1, -2.0)
            hot = m[m > 0]
            out[k] = max(m.max(), -2.0), np.log1p(hot.sum()), np.log1p(len(hot)), len(hot) / max(n, 1)
        return out

    def fit_documents(self, x: np.ndarray, y: np.ndarray) -> None:
        self.center, self.spread = x.mean(0), x.std(0) + 1e-9
        z = np.column_stack([(x - self.center) / self.spread, np.ones(len(x))])
        w = np.zeros(5)
        for _ in range(50):
            p = 1 / (1 + np.exp(-z @ w))
            h = (z * (p * (1 - p) + 1e-6)[:, None]).T @ z + 1e-2 * np.eye(5)
            step = np.linalg.solve(h, z.T @ (y - p) - 1e-2 * w)
            w += np.clip(step, -2, 2)
            if np.abs(step).max() < 1e-8:
                break
        self.coef = w

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.column_stack([(x - self.center) / self.spread, np.ones(len(x))])
        return 1 / (1 + np.exp(-np.clip(z @ self.coef, -30, 30)))


def _fold(marks: list[str], alpha: np.ndarray, bias: float) -> Machine:
    sym, length = _codes(marks)
    table = np.zeros(SYMBOLS**3 + 1)
    share = np.repeat(alpha / _scale(length), REACH)
    for code, weight in _triples(sym):
        np.add.at(table, code.ravel(), weight * share)
    table[-1] = 0  # codes of -1
    return Machine(table.astype(np.float32), bias)


def fit_units(examples: list[tuple[str, float, float]], landmarks: int = LANDMARKS) -> Machine:
    """SVM on Nyström features of units, folded into subsequence weights. examples: (unit, toxic sentences that it stands for, clean ones), both classes present."""
    hot = sorted((x for x in examples if x[1] > 0), key=lambda x: (x[2] - x[1], x[0]))
    cold = sorted((x for x in examples if x[2] > 0), key=lambda x: (x[1] - x[2], x[0]))
    marks = [x[0] for x in hot[: landmarks * 2 // 3]]
    known = set(marks)
    marks += [x[0] for x in cold if x[0] not in known][: landmarks - len(marks)]
    inner = kernel(marks, marks).astype(np.float64)
    value, vector = np.linalg.eigh((inner + inner.T) / 2)
    keep = value > 1e-6 * value.max()
    white = vector[:, keep] / np.sqrt(value[keep])
    z = np.concatenate([np.column_stack([kernel([x[0] for x in part], marks) @ white, np.ones(len(part))]) for part in (hot, cold)])
    y = np.concatenate([np.ones(len(hot)), -np.ones(len(cold))])
    # a unit's weight grows with the root of its sentences, so that none drowns the others; both classes weigh the same
    held = [np.sqrt([x[k] for x in part]) for part, k in ((hot, 1), (cold, 2))]
    cost = len(y) / 2 * np.concatenate([h / h.sum() for h in held])
    w = np.zeros(z.shape[1])
    for _ in range(30):  # Newton steps on the squared hinge
        active = y * (z @ w) < 1
        za, ca = z[active], cost[active]
        new = np.linalg.solve((za * ca[:, None]).T @ za + RIDGE * np.eye(len(w)), za.T @ (ca * y[active]))
        if np.allclose(new, w, atol=1e-9):
            break
        w = new
    return _fold(marks, white @ w[:-1], float(w[-1]))


def held_out(doc_id: object) -> object:
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


def _training(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, text, toxic) of the bounded training sample; of several texts of an id the smallest."""
    own = labels.select(F.col("doc_id").cast("bigint").alias("doc_id"), "toxic").filter("doc_id is not null and toxic is not null").filter(~held_out(F.col("doc_id")))
    chosen = own.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(TRAIN_DOCS)  # the documented bound
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(chosen), "doc_id")
    return rows.groupBy("doc_id").agg(F.min("text").alias("text"), F.max(F.when(F.col("toxic") > 0, 1).otherwise(0)).alias("toxic"))


class Shares:
    """Margins of units before there is a machine: how many standard errors their share of toxic documents lies above that of clean ones, less what chance makes of so many units."""

    def __init__(self, beyond: dict[str, float]) -> None:
        self.beyond = beyond

    def margins(self, words: list[str]) -> np.ndarray:
        return np.array([self.beyond.get(w, -1.0) for w in words])


def _shares(sample: DataFrame, toxic: int, clean: int) -> Shares:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [(t, u) for t, text in zip(b.column(1).to_pylist(), b.column(0).to_pylist(), strict=True) for u in {u for s in sentences(text) for u in s}]
            t, u = zip(*rows, strict=True) if rows else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(t, pa.int32()), pa.array(u, pa.string())], names=["toxic", "word"])

    words = sample.select("text", "toxic").mapInArrow(run, "toxic int, word string")
    counts = words.groupBy("word").agg(F.sum("toxic").alias("t"), F.sum(1 - F.col("toxic")).alias("c"))
    share = (F.col("t") + F.col("c") + 1) / F.lit(toxic + clean + 2)
    z = (F.col("t") / F.lit(toxic) - F.col("c") / F.lit(clean)) / F.sqrt(share * (1 - share) * F.lit(1 / toxic + 1 / clean))
    own = Scratch(sample.sparkSession, "toxicity").save(counts.select("word", z.alias("z")), "shares")
    chance = float(np.sqrt(2 * np.log(max(own.count(), 2))))
    return Shares({w: x - chance for w, x in own.filter(F.col("z") > chance).collect()})  # of at most TRAIN_DOCS documents, units that tell the classes apart


def _units(sample: DataFrame, machine: Machine | Shares, toxic: int, clean: int) -> list[tuple[str, float, float]]:
    """(unit, toxic sentences that it stands for, clean ones). Clean labels hold for every sentence, toxic ones do not: a unit that clean sentences have at SHARED of its rate in toxic ones is clean."""
    held = kept_in_workers(sample.sparkSession, machine)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [sentences(t) for t in b.column(1).to_pylist()]
            every = sorted({u for text in texts for s in text for u in s})
            value = dict(zip(every, held().margins(every).tolist(), strict=True)) if every else {}
            rows = []
            for i, t, text in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), texts, strict=True):
                worst = sorted(((value[u], u) for u in (max(s, key=lambda u: (value[u], u)) for s in text)), reverse=True)[:SENTENCES]
                rows += [(u, t) for k, (m, u) in enumerate(worst) if m > 0 or not t and k < WORST]
                if not t:
                    drawn = sorted({u for s in text for u in s}, key=lambda u: zlib.crc32(f"{i} {u}".encode("utf-8", "surrogatepass")))
                    rows += [(u, 0) for u in drawn[:DRAWN]]
            u, t = zip(*rows, strict=True) if rows else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.string()), pa.array(t, pa.int32())], names=["word", "toxic"])

    rows = sample.select("doc_id", "text", "toxic").mapInArrow(run, "word string, toxic int")
    counts = rows.groupBy("word").agg(F.sum("toxic").cast("double").alias("hot"), F.sum(1 - F.col("toxic")).cast("double").alias("cold")).orderBy("word").collect()  # some a document of the sample
    return [(w, 0.0 if cold / clean >= SHARED * hot / toxic else hot, cold) for w, hot, cold in counts if hot or cold]


def train(docs: DataFrame, labels: DataFrame) -> tuple[Machine | None, float]:
    """A fitted machine, or None where one class is missing; and the share of toxic training labels."""
    spark = docs.sparkSession
    sample = Scratch(spark, "toxicity").save(_training(docs, labels).repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "doc_id").sortWithinPartitions("doc_id"), "sample")
    n = {bool(t): c for t, c in sample.groupBy(F.col("toxic") > 0).count().collect()}
    toxic, clean = n.get(True, 0), n.get(False, 0)
    prior = toxic / max(toxic + clean, 1)
    if not toxic or not clean:
        return None, prior
    machine, by = None, _shares(sample, toxic, clean)
    for _ in range(ROUNDS):
        examples = _units(sample, by, toxic, clean)
        if not any(x[1] for x in examples) or not any(x[2] for x in examples):
            break
        by = machine = fit_units(examples)
    if machine is None:
        return None, prior

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = machine.document(b.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([*(pa.array(x[:, k]) for k in range(4)), b.column(1).cast(pa.int32())], names=["a", "b", "c", "d", "toxic"])

    rows = sample.select("text", F.col("toxic").cast("int")).mapInArrow(run, "a double, b double, c double, d double, toxic int").toPandas()
    machine.fit_documents(rows[["a", "b", "c", "d"]].to_numpy(), (rows["toxic"] > 0).to_numpy().astype(float))
    return machine, prior


def score(docs: DataFrame, machine: Machine | None, prior: float = 0.0) -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(2).to_pylist()
            s = np.concatenate([machine.score(machine.document(texts[k : k + 2000])) for k in range(0, len(texts), 2000)]) if machine and texts else np.full(len(texts), prior)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(s), pa.array((s >= THRESHOLD).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, held_out boolean, score double, predicted int")


def op2_toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    return score(docs, *train(docs, labels))
