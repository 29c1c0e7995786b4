"""Words of many texts at once: a word is a maximal run of letters and digits of the lowered text."""

from __future__ import annotations

import numpy as np

_BASE = 0x9E3779B97F4A7C15
_WORD = np.array([chr(i).isalnum() for i in range(0x110000)], bool)
_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    held = _POWERS.get(base)
    if held is None or len(held) < n:
        held = np.full(max(n, 1 << 16), base, np.uint64)
        held[0] = 1
        held = _POWERS[base] = np.cumprod(held, dtype=np.uint64)
    return held[:n]


class Words:
    """``hashes``: 64-bit hash of each word; ``first``: number of the first word of each text, and the total."""

    def __init__(self, texts: list[str]):
        low = [t.lower() for t in texts]
        joined = "\n".join(low) + "\n"
        self.code = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), "<u4")
        word = _WORD[self.code]
        edge = np.flatnonzero(word[1:] != word[:-1]) + 1
        if len(word) and word[0]:
            edge = np.concatenate([[0], edge])
        self.opens, self.ends = edge[0::2], edge[1::2]
        self.stops = np.cumsum([len(t) + 1 for t in low]) if low else np.zeros(0, np.int64)
        self.first = np.concatenate([[0], np.searchsorted(self.opens, self.stops)])
        n = len(self.code)
        sums = np.zeros(n + 1, np.uint64)
        np.cumsum((self.code + np.uint64(1)) * _powers(_BASE, n), out=sums[1:])
        h = (sums[self.ends] - sums[self.opens]) * _powers(pow(_BASE, -1, 1 << 64), n)[self.opens]
        self.hashes = mixed(h + (self.ends - self.opens).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def shingles(words: Words, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each run of ``size`` words within a text, and where each text's begin (and the total).

    A text with fewer words, but one at least, has one shingle of all its words.
    """
    first, h = words.first, words.hashes
    counts = np.diff(first)
    run = np.zeros(max(0, len(h) - size + 1), np.uint64)
    for i in range(size):
        run = run * np.uint64(0x9E3779B97F4A7C15) + h[i : i + len(run)] if len(run) else run
    run = mixed(run)
    many = np.maximum(counts - size + 1, (counts > 0).astype(np.int64))
    starts = np.concatenate([[0], np.cumsum(many)])
    at = np.repeat(first[:-1] - starts[:-1], many) + np.arange(starts[-1])
    out = np.zeros(starts[-1], np.uint64)
    full = np.repeat(counts >= size, many)
    out[full] = run[at[full]]
    for t in np.flatnonzero((counts > 0) & (counts < size)).tolist():
        own = np.zeros(1, np.uint64)
        for w in h[first[t] : first[t + 1]]:
            own = own * np.uint64(0x9E3779B97F4A7C15) + w
        out[starts[t]] = mixed(own + np.uint64(counts[t]))[0]
    return out, starts
