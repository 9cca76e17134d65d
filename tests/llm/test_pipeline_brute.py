"""run() against the five stages in plain Python, on documents with near copies, repeated rows, shared lines and shared passages."""

import collections
import re
import unicodedata
import zlib

import numpy as np

import corpus_pipeline
from tests.llm.test_nearcopies import brute_kept
from tests.llm.test_short_lines import brute as brute_lines
from tilestar.llm import bpe, packing

WHITE = " \t\n\x0b\x0c\r"


def words(text):
    return [w for w in re.split(f"[{WHITE}]+", text or "") if w]


def accepted(text):
    w, t = words(text), text or ""
    lines = [x for x in t.split("\n") if x.strip(WHITE)]
    runs = collections.defaultdict(list)
    for k in range(len(w) - 7):
        runs[tuple(w[k : k + 8])].append(k)
    again = {k + j for places in runs.values() if len(places) > 1 for k in places for j in range(8)}
    chars = sum(map(len, w))
    return not (
        len(w) < 20
        or 100 * len(again) > 30 * len(w)
        or 20 * sum(c in "#*$%&|<>" for c in t) > chars
        or 2 * (len(lines) - len(set(lines))) > len(lines)
        or 5 * sum(a == b for a, b in zip(w, w[1:], strict=False)) > len(w)
        or 2 * sum(unicodedata.category(c) == "Lu" for c in t) > chars
        or chars < 3 * len(w)
        or chars > 12 * len(w)
    )


def without_passages(rows, window=35):
    own = [(i, t, words(t)) for i, t in rows]
    n = collections.Counter(tuple(w[k : k + window]) for _, _, w in own for k in range(len(w) - window + 1))
    out = []
    for i, t, w in own:
        gone = {k + j for k in range(len(w) - window + 1) if n[tuple(w[k : k + window])] > 1 for j in range(window)}
        out.append((i, " ".join(x for k, x in enumerate(w) if k not in gone) if gone else t))
    return out


def corpus():
    rng = np.random.default_rng(12)
    vocabulary = [f"{a}{b}" for a in ("river", "stone", "cloud", "paper", "green") for b in "abcdefghijklmnop"]
    line = lambda n: " ".join(str(x) for x in rng.choice(vocabulary, n))
    passage, shared, rows = line(50), line(30), []
    for k in range(24):
        text = "\n".join(line(int(rng.integers(12, 40))) for _ in range(int(rng.integers(2, 5))))
        if k % 5 == 0:
            text = f"{line(25)} {passage} {line(int(rng.integers(3, 9)))}\n{text}"
        if k % 7 == 0:
            text += f"\n{shared}"
        rows.append((k, text))
    long = line(120).split()
    for k in range(4):  # near copies on one line, which differ by a word
        own = list(long)
        own[10 + 20 * k : 12 + 20 * k] = [f"other{k}", f"word{k}"]
        rows.append((40 + k, " ".join(own)))
    return [*rows, rows[3], rows[3], (60, rows[5][1]), (61, "too short"), (62, "x% y% z% " * 20), (63, None)]


def test_run_by_brute_force(spark, tmp_path):
    rows = corpus()
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()

    kept = sorted((i, t) for i, t in rows if accepted(t))
    once = sorted(set(kept))  # repeated rows are one document to the line stage, and one stays after the next
    lined = brute_lines(once)
    ids = set(brute_kept([(i, t, "en") for i, t in lined]))
    last = without_passages([(i, t) for i, t in lined if i in ids])
    assert len(last) < len(once) < len(kept) < len(rows) and any(t != dict(lined)[i] for i, t in last)

    codec, want = bpe.Codec(bpe.default_path()), collections.Counter()
    for (i, _), ids in zip(last, codec.encode([t for _, t in last]), strict=True):
        ids = np.append(ids, packing.END).astype("<u4")
        want.update((i, k, at, n, zlib.crc32(ids[at : at + n].tobytes())) for k, (at, n) in enumerate(packing.cuts(len(ids))))
    assert collections.Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    sequences = collections.defaultdict(list)
    for r in got:
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in sequences.values():
        own.sort()
        assert [at for at, _ in own] == [sum(n for _, n in own[:k]) for k in range(len(own))] and sum(n for _, n in own) <= packing.CAPACITY
    histogram = np.bincount([r["length"] for r in got], minlength=packing.CAPACITY + 1)
    assert len(sequences) == packing.solve(histogram)[1]  # as few as the proven bound
