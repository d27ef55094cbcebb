"""Words, word hashes, shingles and MinHash values of whole batches of texts, computed with array operations.

A word's hash is a polynomial over its bytes, read from prefix sums, so no Python code runs per word. Words are the
runs `[^\\x20\\x09-\\x0D]+`; A-Z count as a-z.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = np.asarray(x, U)
    with np.errstate(over="ignore"):
        x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def stream(seed: int, n: int) -> np.ndarray:
    """n fixed pseudo-random 64-bit numbers."""
    with np.errstate(over="ignore"):
        return mix(np.arange(1, n + 1, dtype=U) * U(0xD1342543DE82EF95) + U(seed * 0x632BE59BD9B4E019 & (1 << 64) - 1))


SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BYTE = stream(11, 256)[LOWER]


def _power(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, 1 << 16), U(base))
        have[0] = 1
        have = np.multiply.accumulate(have)
        if len(have) <= 1 << 23:
            _powers[base] = have
    return have[:n]


def word_spans(values: np.ndarray, offsets: np.ndarray, breaks: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of every word, and n + 1 offsets of the documents in the list of words."""
    if not len(values):
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offsets), np.int64)
    gap = breaks[values]
    cut = np.zeros(len(values) + 1, bool)
    cut[offsets] = True
    word = ~gap
    before = np.empty(len(values), bool)
    before[0] = True
    np.logical_or(gap[:-1], cut[1:-1], out=before[1:])
    after = np.empty(len(values), bool)
    after[-1] = True
    np.logical_or(gap[1:], cut[1:-1], out=after[:-1])
    starts = np.flatnonzero(word & before)
    ends = np.flatnonzero(word & after) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of byte spans, equal for spans that differ in the case of A-Z only."""
    n = len(values)
    with np.errstate(over="ignore"):
        run = np.zeros(n + 1, U)
        np.cumsum(_BYTE[values] * _power(_BASE, n), out=run[1:])
        h = (run[ends] - run[starts]) * _power(_INVERSE, n + 1)[starts]
        return mix(h + (ends - starts).astype(U))


_COMBINE = stream(12, 16) | U(1)


def combine(columns: list[np.ndarray]) -> np.ndarray:
    """One hash of several in a fixed order."""
    with np.errstate(over="ignore"):
        total = np.full(columns[0].shape, U(len(columns)))
        for c, m in zip(columns, _COMBINE, strict=False):
            total = (total ^ (total >> U(29))) + c * m
    return mix(total)


def shingles(words: np.ndarray, k: int) -> np.ndarray:
    """Distinct k-word shingles of one document's word hashes, sorted; fewer words make one shingle; none make none."""
    if not len(words):
        return words
    if len(words) < k:
        return combine([words[i : i + 1] for i in range(len(words))])
    return np.unique(combine([words[i : len(words) - k + 1 + i] for i in range(k)]))


class MinHash:
    """n multiply-add permutations of 64-bit hashes."""

    def __init__(self, n: int, seed: int = 21):
        self.a, self.b = stream(seed, n) | U(1), stream(seed + 1, n)

    def __call__(self, hashes: np.ndarray, block: int = 1024) -> np.ndarray:
        out = np.full(len(self.a), U((1 << 64) - 1))
        with np.errstate(over="ignore"):
            for i in range(0, len(hashes), block):
                x = hashes[i : i + block, None] * self.a
                x += self.b
                np.minimum(out, x.min(axis=0), out=out)
        return out
