"""The pipeline's near-dedup stage against brute force."""

import numpy as np
import pytest

import corpus_pipeline
from tilestar.llm import nearcopies

SCHEMA = "doc_id bigint, text string, lang string"


def brute_kept(rows):
    """Ids that stay, by all pairs of five-word shingle sets; ids are distinct and not null."""

    def sets(text):
        w = (text or "").lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    own, parent = [sets(t) for _, t, _ in rows], list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(own):
        for j in range(i):
            if 5 * len(a & own[j]) >= 4 * len(a | own[j]):
                parent[find(i)] = find(j)
    least = {}
    for k, (i, *_) in enumerate(rows):
        least[find(k)] = min(i, least.get(find(k), i))
    return sorted(least.values())


def corpus():
    rng = np.random.default_rng(4)
    words = [f"w{k}" for k in range(3000)]
    common = [f"c{k}" for k in range(30)]
    rows = []
    for base in range(25):
        text = [str(x) for x in rng.choice(words, rng.integers(4, 150))]
        if base % 3 == 0:
            text = common + text
        for _ in range(8):
            own = list(text)
            for _ in range(rng.integers(0, 4)):
                own[rng.integers(len(own))] = str(rng.choice(words))
            rows.append((len(rows), " ".join(own).upper() if rng.random() < 0.1 else "  ".join(own), "en"))
    long = [str(x) for x in rng.choice(words, 100)]
    rows += [(1000 + k, " ".join(long[:k] + [f"y{k}"] + long[k + 1 :]), "en") for k in range(0, 100, 2)]  # all near copies of one text
    rows += [(2000 + k, " ".join(long[k : k + 60]), "en") for k in range(0, 40, 4)]  # a chain
    rows += [(3000, None, None), (3001, "", "en"), (3002, " \n", "en"), (3003, "a b", "en"), (3004, "A  b", "en"), (3005, "a b c", "en")]
    return rows


@pytest.mark.parametrize("often", [4, 1])
def test_near_copies_by_brute_force(spark, monkeypatch, often):
    monkeypatch.setattr(nearcopies, "OFTEN", often)
    rows = corpus()
    got = corpus_pipeline.near_dedup(spark, spark.createDataFrame(rows, SCHEMA), "")
    assert got.columns == ["doc_id", "text", "lang"]
    want = brute_kept(rows)
    assert sorted(r["doc_id"] for r in got.collect()) == want and len(want) < len(rows) // 2


def test_members_unlike_their_lists_first_are_compared(spark):
    word = [f"w{k}" for k in range(400)]
    # all share the rare start; only the last two are near copies, and neither resembles the first
    rows = [(k, " ".join(word[:30] + [f"d{k}x{j}" for j in range(70)]), "en") for k in range(20)]
    rows += [(50, rows[19][1] + " tail", "en")]
    got = nearcopies.keep_one(spark.createDataFrame(rows, SCHEMA).repartition(3))
    assert sorted(r["doc_id"] for r in got.collect()) == list(range(20)) == brute_kept(rows)


def test_empty_table(spark):
    assert nearcopies.keep_one(spark.createDataFrame([], SCHEMA)).count() == 0


def test_simhash_trie_has_its_part(spark, monkeypatch):
    """What the trie proposes is confirmed on the texts, by pairs of few differing bits, and the exact join is left without pairs where the trie has linked all."""
    word = [f"w{k}" for k in range(2000)]
    rows = [(k, " ".join([*word[: 900 + k], "end"]), "en") for k in range(12)] + [(50, "something else in seven words of text", "en")]
    met = {}
    verified = nearcopies._verified

    def spy(pairs, *rest):
        edges = verified(pairs, *rest)
        met[rest[-1]] = edges.count()
        return edges

    monkeypatch.setattr(nearcopies, "_verified", spy)
    got = corpus_pipeline.near_dedup(spark, spark.createDataFrame(rows, SCHEMA), "")
    assert sorted(r["doc_id"] for r in got.collect()) == [0, 50] == brute_kept(rows)
    assert met["trie"] >= 1 and met["trie"] + met["first"] + met["more"] <= 2 * len(rows)
    sets = [nearcopies.shingles(t) for _, t, _ in rows]
    differing = lambda a, b: int((nearcopies.simhash_of(a) ^ nearcopies.simhash_of(b)) & (2**64 - 1)).bit_count()
    assert differing(sets[0], sets[1]) <= 4 < 15 < differing(sets[0], sets[-1])
