"""Licence notices wrapped over lines or inside longer ones."""

import textwrap

import numpy as np

from tilestar.llm import licenses


def test_wrapped_and_embedded_notices():
    s = licenses.Scanner()
    prose = " ".join(f"word{k}" for k in range(400))
    for name, text in licenses.TEMPLATES:
        wrapped = "\n".join(" * " + x for x in textwrap.wrap(text, 40))
        assert s.scan(f"{prose}\n{wrapped}\n{prose}")[:2] == (name, 1.0)
        assert s.scan(f"{prose} {text} {prose}")[:2] == (name, 1.0)
    assert s.scan(f"{prose} Released under the MIT License. {prose} Licensed under CC BY 4.0. {prose}") == ("CC-BY-4.0", 1.0, 2)
    assert s.scan(f"{prose}\nReleased under the MIT License.\n{prose}") == ("MIT", 1.0, 1)


def test_passages_by_brute_force():
    rng = np.random.default_rng(1)
    s = licenses.Scanner((("x", "a b c d e a c"), ("y", "b d b e")), 0.8)
    for _ in range(150):
        w = [str(x) for x in rng.choice(list("abcdeff"), rng.integers(2, 30))]
        want = max(2 * len(own & t) / (len(own) + len(t)) for i in range(len(w)) for j in range(i + 2, len(w) + 1) if (own := licenses.bigrams(" ".join(w[i:j]))) for _, t in s.templates)
        assert s.scan(" ".join(w))[1] == (want if want >= 0.8 else 0.0)
