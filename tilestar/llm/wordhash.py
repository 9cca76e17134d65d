"""Vectorised 64-bit hashes of words and word windows of a text, with NumPy over its bytes."""

from __future__ import annotations

import numpy as np

U = np.uint64
#: One odd multiplier; sums run modulo 2^64.
STEP = U(0x9E3779B97F4A7C15 | 1)
_WHITE = np.zeros(256, bool)
_WHITE[[9, 10, 11, 12, 13, 32]] = True
_BYTE = np.random.Generator(np.random.PCG64(20240229)).integers(1, 1 << 63, 256, np.int64).astype(U)
_BYTE[_WHITE] = 0


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection on 64 bits that spreads every bit."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
        return x ^ (x >> U(31))


def words(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, hashes) of the words of a text, as byte places."""
    raw = np.frombuffer(data, np.uint8)
    solid = ~_WHITE[raw]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], solid, [False])).view(np.int8)))
    starts, ends = edge[::2], edge[1::2]
    if not len(starts):
        return starts, ends, np.zeros(0, U)
    lengths = ends - starts
    longest = int(lengths.max())
    with np.errstate(over="ignore"):
        power = np.cumprod(np.concatenate((np.ones(1, U), np.full(longest - 1, STEP, U))), dtype=U)
        inside = np.flatnonzero(solid)
        first = np.cumsum(lengths) - lengths
        place = np.arange(len(inside)) - np.repeat(first, lengths)
        total = np.add.reduceat(_BYTE[raw[inside]] * power[place], first)
        return starts, ends, mix(total + lengths.astype(U) * U(0xD6E8FEB86659FD93))


def windows(h: np.ndarray, width: int) -> np.ndarray:
    """Hash of every run of `width` hashes, by doubling."""
    if len(h) < width:
        return np.zeros(0, U)
    out, have, power, block, size = None, 0, STEP, h, 1
    shift = U(1)
    with np.errstate(over="ignore"):
        while True:
            if width & size:
                if out is None:
                    out, have, shift = block, size, power
                else:
                    n = len(h) - have - size + 1
                    out = out[:n] + shift * block[have : have + n]
                    have, shift = have + size, shift * power
            size *= 2
            if size > width:
                return mix(out[: len(h) - width + 1])
            n = len(block) - size // 2
            block = block[:n] + power * block[size // 2 : size // 2 + n]
            power = power * power


def lowest(x: np.ndarray, width: int) -> np.ndarray:
    """For every run of `width` values, the place of its first smallest."""
    n = len(x) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    at, size = np.arange(len(x)), 1
    while size < width:
        by = min(size, width - size)
        left, right = at[: len(at) - by], at[by:]
        at = np.where(x[right] < x[left], right, left)
        size += by
    return at[:n]
