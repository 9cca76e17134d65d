"""The configuration program against optima and its own bound."""

import collections
import functools

import numpy as np
import pytest

from tilestar.llm import packing


def solved(histogram, capacity=1024):
    h = np.zeros(capacity + 1, np.int64)
    for n, k in histogram.items():
        h[n] = k
    configs, bound = packing.solve(h, capacity)
    got = np.zeros(capacity + 1, np.int64)
    for config, many in configs:
        assert sum(n * k for n, k in config.items()) <= capacity and many > 0
        for n, k in config.items():
            got[n] += k * many
    assert (got == h).all()
    used = sum(many for _, many in configs)
    assert bound <= used
    return used, bound


def optimum(pieces, capacity):
    """Fewest sequences, by search over which pieces share one."""

    @functools.cache
    def best(left):
        if not left:
            return 0
        first, rest = left[0], left[1:]
        found = len(left)
        for mask in range(1 << len(rest)):
            own = [x for k, x in enumerate(rest) if mask >> k & 1]
            if first + sum(own) <= capacity:
                found = min(found, 1 + best(tuple(x for k, x in enumerate(rest) if not mask >> k & 1)))
        return found

    return best(tuple(sorted(pieces, reverse=True)))


def test_a_histogram_that_greedy_filling_gets_wrong():
    assert solved({513: 1000, 300: 3000, 260: 2000, 205: 4000}) == (2750, 2750)


def test_small_histograms_are_optimal():
    rng = np.random.default_rng(3)
    for _ in range(40):
        pieces = [int(x) for x in rng.integers(1, 21, rng.integers(1, 10))]
        used, bound = solved(collections.Counter(pieces), 20)
        assert used == optimum(pieces, 20) >= bound


@pytest.mark.parametrize("low,high,gap", [(1, 1024, 0.006), (300, 700, 0.01), (400, 520, 0.01)])
def test_gap_to_the_bound_on_many_lengths(low, high, gap):
    x = np.random.default_rng(1).integers(low, high, 4000)
    used, bound = solved(dict(zip(*(v.tolist() for v in np.unique(x, return_counts=True)), strict=True)))
    assert used <= bound * (1 + gap) + 1


def test_empty_full_and_single():
    assert solved({}) == (0, 0) and solved({1024: 7}) == (7, 7) and solved({5: 1}) == (1, 1)


def test_knapsacks_agree():
    rng = np.random.default_rng(2)
    for _ in range(20):
        lengths = np.unique(rng.integers(1, 60, 12))
        price = rng.random(len(lengths))
        one, other = packing.dearest(price, lengths, np.full(len(lengths), 100), 100), packing.dearest_free(price, lengths, 100)
        value = dict(zip(lengths.tolist(), price.tolist(), strict=True))
        worth = [sum(value[n] * k for n, k in c.items()) for c in (one, other)]
        assert abs(worth[0] - worth[1]) < 1e-9 and all(sum(n * k for n, k in c.items()) <= 100 for c in (one, other))
