"""Vectorised word hashing: every word of a batch of texts in a few numpy passes.

A word's hash is a polynomial over random byte values, modulo 2**64, taken from a running sum and
then mixed. Words are runs of bytes that ``is_space`` does not list; texts never share words.
"""

from __future__ import annotations

import numpy as np

_MASK = (1 << 64) - 1
_C = 0x9E3779B97F4A7C15 | 1
SPACES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (in place)."""
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_VALUES = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))
_LOWER = np.arange(256)
_LOWER[65:91] += 32


class WordHasher:
    """``fold``: A-Z count as a-z. ``punctuation_is_space``: ASCII punctuation separates words.
    Hashes of different seeds are independent."""

    def __init__(self, *, fold: bool = True, punctuation_is_space: bool = False, seed: int = 0):
        values = _VALUES if not seed else mix(_VALUES + np.uint64(0xA0761D6478BD642F) * np.uint64(seed))
        self.values = values[_LOWER] if fold else values
        self.base = (_C + 8 * seed * 0x632BE59BD9B4E019) & _MASK
        self.is_space = np.zeros(256, bool)
        self.is_space[list(SPACES)] = True
        if punctuation_is_space:
            for lo, hi in ((33, 48), (58, 65), (91, 97), (123, 127)):
                self.is_space[lo:hi] = True
        self.up = self.down = np.zeros(0, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            n = (n + (1 << 18) - 1) >> 18 << 18
            with np.errstate(over="ignore"):
                self.up = np.cumprod(np.full(n, self.base, np.uint64))
                self.down = np.cumprod(np.full(n, pow(self.base, -1, 1 << 64), np.uint64))

    def rest(self) -> None:
        """Drops the tables that grew with the blocks."""
        self.up = self.down = np.zeros(0, np.uint64)

    def _block(self, data: np.ndarray, prefixes: tuple[int, ...]) -> tuple[list[np.ndarray], np.ndarray]:
        """Hashes of the words of a block that starts and ends with a space; where they start."""
        self._powers(len(data))
        edge = np.diff(self.is_space[data].view(np.int8))
        start, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)  # both just before
        total = np.cumsum(self.values[data] * self.up[: len(data)])
        ends = [end, *(np.minimum(end, start + k) for k in prefixes)]
        return [mix((total[e] - total[start]) * self.down[start]) for e in ends], start

    def prefixed(self, texts: list[bytes], prefixes: tuple[int, ...], block: int = 1 << 20) -> tuple[list[np.ndarray], np.ndarray]:
        """Hashes of all words and of their first so many bytes, and where each text's words
        begin (one more entry than texts)."""
        hashes, counts, at = [], [], 0
        while at < len(texts):
            first, size = at, 1
            while at < len(texts) and (at == first or size + len(texts[at]) < block):
                size += len(texts[at]) + 1
                at += 1
            joined = b" " + b" ".join(texts[first:at]) + b" "
            h, start = self._block(np.frombuffer(joined, np.uint8), prefixes)
            bounds = np.cumsum([0, *(len(t) + 1 for t in texts[first:at])])
            hashes.append(h)
            counts.append(np.diff(np.searchsorted(start, bounds)))
        n = np.concatenate(counts) if counts else np.zeros(0, np.int64)
        whole = [np.concatenate(x) for x in zip(*hashes)] or [np.zeros(0, np.uint64)] * (1 + len(prefixes))
        return whole, np.concatenate([[0], np.cumsum(n)]).astype(np.int64)

    def texts(self, texts: list[bytes], block: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
        """All word hashes in order, and where each text's words begin."""
        (h,), at = self.prefixed(texts, (), block)
        return h, at


def windows(hashes: np.ndarray, bounds: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each run of k words inside a text, and the texts' bounds among them. A text with
    1 to k-1 words has one window, its whole sequence; a text without words has none."""
    n = np.diff(bounds)
    if len(hashes) == 0:
        return hashes, np.zeros(len(bounds), np.int64)
    pad = np.concatenate([hashes, np.zeros(k - 1, np.uint64)])
    h = np.zeros(len(hashes), np.uint64)
    for i in range(k):
        h = h * np.uint64(_C) + pad[i : i + len(hashes)]
    h = mix(h)
    m = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    out = np.concatenate([[0], np.cumsum(m)]).astype(np.int64)
    pick = np.arange(out[-1]) + np.repeat(bounds[:-1] - out[:-1], m)
    h = h[pick]
    for i in np.flatnonzero((n > 0) & (n < k)):
        x = np.uint64(n[i])
        for w in hashes[bounds[i] : bounds[i + 1]]:
            x = np.uint64((int(x) * _C + int(w)) & _MASK)
        h[out[i]] = mix(np.asarray([x], np.uint64))[0]
    return h, out


def blocks(texts: list[bytes], size: int = 2 << 20):
    """Consecutive runs of texts of about ``size`` bytes, so that working arrays stay small."""
    at = 0
    while at < len(texts):
        first, total = at, 0
        while at < len(texts) and (at == first or total + len(texts[at]) <= size):
            total += len(texts[at])
            at += 1
        yield texts[first:at]
