"""The subsequence kernel against its definition, and the folded machine against kernel times weights."""

import itertools

import numpy as np

from tilestar.llm import toxicity


def naive(a, b):
    """Sum over common subsequences of three characters within SPAN, each occurrence weighted by DECAY to its span."""

    def marks(word):
        w, out = f"{toxicity.EDGE}{word}{toxicity.EDGE}", {}
        w = "".join(toxicity.STANDS_FOR.get(c, c) for c in w)
        for i, j, k in itertools.combinations(range(len(w)), 3):
            if k - i < toxicity.SPAN:
                out[w[i] + w[j] + w[k]] = out.get(w[i] + w[j] + w[k], 0.0) + toxicity.DECAY ** (k - i + 1)
        return out

    x, y = marks(a), marks(b)
    scale = lambda w: toxicity._scale(np.array([len(w) + 2]))[0]
    return sum(v * y.get(s, 0.0) for s, v in x.items()) / scale(a) / scale(b)


def test_kernel_by_definition():
    words, marks = ["idiot", "i-d-iot", "1d10t", "banana", "xyz", "aaaaaa"], ["idiot", "banana", "stupid", "aaab"]
    want = np.array([[naive(a, b) for b in marks] for a in words])
    assert np.allclose(toxicity.kernel(words, marks), want, atol=1e-5)
    assert want[1, 0] > 0.3 > want[3, 0]


def test_folded_weights_are_kernel_times_alpha():
    marks, words, alpha = ["idiot", "window", "clown"], ["idi0t", "widow", "clowns", "tree"], np.array([1.5, -0.5, 0.25])
    machine = toxicity._fold(marks, alpha, -0.1)
    assert np.allclose(machine.margins(words), toxicity.kernel(words, marks) @ alpha - 0.1, atol=1e-4)


def test_gapped_and_stuffed_insults_follow_from_plain_ones():
    cold = [f"{a}{b}{c}" for a, b, c in itertools.product(("win", "tab", "gar"), ("dow", "le", "den"), ("s", "ly", "er"))]
    machine = toxicity.fit_units([("idiot", 9.0, 0.0), ("moron", 7.0, 0.0), *((w, 0.0, 3.0) for w in cold)])
    hot, plain = machine.margins(["id-iot", "i.diot", "idiiot", "m0ron", "mooron"]), machine.margins(["garden", "tables", "harden", "cable"])
    assert hot.min() > plain.max()


def test_sentences():
    assert toxicity.sentences("You are i d i o t. What\nnow? ") == [["are", "idiot", "you"], ["what"], ["now"]]
    assert toxicity.sentences(None) == [] == toxicity.sentences(" a b ")


def test_held_out_accuracy(spark):
    """On the labels that training never sees."""
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    got = toxicity.op2_toxicity(docs, labels).filter("held_out").join(labels.groupBy("doc_id").agg({"toxic": "max"}).toDF("doc_id", "toxic"), "doc_id")
    n = {(r["toxic"], r["predicted"]): r["count"] for r in got.groupBy("toxic", "predicted").count().collect()}
    assert n[1, 1] >= 0.9 * (n[1, 1] + n.get((1, 0), 0)) and n.get((0, 1), 0) <= 0.04 * (n[0, 0] + n.get((0, 1), 0)), n
