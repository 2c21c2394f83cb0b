"""Vectorised hashing of byte and word sequences: prefix polynomial hashes, words, minimizers.

A sequence x is hashed as sum(T(x[i]) * b**i) modulo 2**64 with T a table (or mix) of random 64-bit
values, so that one cumulative sum gives every window's hash by a subtraction and a shift by b**-i.
"""

from __future__ import annotations

import numpy as np

U = np.uint64
CHUNK = 1 << 19
_POS_BITS = 21


class Memo(dict):
    """A cache of one process: pickled, it is empty."""

    def __reduce__(self):
        return Memo, ()


_powers = Memo()


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64 bits (the published splitmix64 constants)."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def stream(n: int, seed: int) -> np.ndarray:
    """n pseudo-random 64-bit values that depend on the seed alone."""
    start = (seed * 0xD1B54A32D192ED03 + 0x632BE59BD9B4E019) % (1 << 64)
    return mix(np.arange(1, n + 1, dtype=np.uint64) * U(0x9E3779B97F4A7C15) + U(start))


def powers(seed: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """b**i and b**-i for i < n; b is odd and so has an inverse modulo 2**64."""
    held = _powers.get(seed)
    if held is None or len(held[0]) < n:
        base = (int(stream(1, seed ^ 0x5EED)[0]) | 5) % (1 << 64)
        size = max(n, CHUNK + 4096)
        out = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.full(size, b, dtype=np.uint64)
            p[0] = 1
            out.append(np.multiply.accumulate(p))
        held = _powers[seed] = (out[0], out[1])
    return held


class PrefixHash:
    """Window hashes of one sequence. For bytes, values come from a table; 64-bit tokens are mixed."""

    def __init__(self, tokens: np.ndarray, seed: int = 1):
        self.power, self.inverse = powers(seed, len(tokens) + 1)
        values = stream(256, seed)[tokens] if tokens.dtype == np.uint8 else mix(tokens ^ stream(1, seed)[0])
        self.sums = np.zeros(len(tokens) + 1, dtype=np.uint64)
        np.cumsum(values * self.power[: len(tokens)], out=self.sums[1:])

    def windows(self, length: int) -> np.ndarray:
        """The hash of every window of this length, by its start."""
        n = len(self.sums) - length
        return (self.sums[length:] - self.sums[:n]) * self.inverse[:n] if n > 0 else np.zeros(0, np.uint64)

    def spans(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The hash of tokens [start, end) of each pair, the same wherever the tokens stand."""
        return (self.sums[end] - self.sums[start]) * self.inverse[start]


SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True


def word_bounds(text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of bytes other than 0x20 and 0x09 to 0x0D."""
    inside = np.zeros(len(text) + 2, dtype=np.int8)
    inside[1:-1] = ~SPACE[text]
    edge = np.diff(inside)
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def sliding_min(a: np.ndarray, width: int) -> np.ndarray:
    """min(a[i : i + width]) for every i."""
    span = 1
    while 2 * span <= width:
        a = np.minimum(a[:-span], a[span:])
        span *= 2
    return np.minimum(a[: len(a) - (width - span)], a[width - span :]) if span < width else a


def anchored_runs(tokens: np.ndarray, ends: np.ndarray, length: int, shingle: int, seed: int = 1):
    """Runs of consecutive windows that have one minimizer, over a flat array of documents.

    ends: the end of the document at each token. Every window of `length` tokens that lies inside a
    document belongs to exactly one run; its anchor is the leftmost least hash among its shingles,
    so equal windows have equal anchors at equal offsets. Returns per run: first window, number of
    windows, anchor position and anchor hash. Works in chunks, so memory does not follow the array.
    """
    n, parts = len(tokens), []
    width = length - shingle + 1
    for lo in range(0, max(0, n - length + 1), CHUNK):
        part = tokens[lo : lo + CHUNK + length - 1]
        hashes = mix(PrefixHash(part, seed).windows(shingle))
        low = U((1 << _POS_BITS) - 1)
        at = sliding_min((hashes & ~low) | np.arange(len(hashes), dtype=np.uint64), width) & low
        count = len(part) - length + 1
        start = np.arange(lo, lo + count)
        valid = ends[lo : lo + count] - start >= length
        first = valid.copy()
        first[1:] &= (at[1:] != at[:-1]) | ~valid[:-1]
        begin = np.flatnonzero(first)
        if len(begin):
            done = valid.copy()
            done[:-1] &= first[1:] | ~valid[1:]
            anchor = at[begin].astype(np.int64)
            parts.append((begin + lo, np.flatnonzero(done) - begin + 1, anchor + lo, hashes[anchor]))
    if not parts:
        empty = np.zeros(0, dtype=np.int64)
        return empty, empty, empty, empty.astype(np.uint64)
    return tuple(np.concatenate(x) for x in zip(*parts, strict=True))
