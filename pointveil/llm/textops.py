"""Vectorised tokens of many texts at once: word bounds, word hashes and character n-gram hashes on one byte buffer."""

from __future__ import annotations

import numpy as np

_RNG = np.random.default_rng(20240101)
_BYTE = _RNG.integers(1, 1 << 63, 256, dtype=np.uint64)
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, np.uint64(base))
    out[:1] = 1
    return np.multiply.accumulate(out)


def mix(x: np.ndarray) -> np.ndarray:
    """Spread all bits of 64-bit words."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


class Words:
    """White-space words of texts.

    ``doc``: text number of each word; ``start``, ``end``: its bytes in ``buffer``; ``sizes``: words of each text.
    """

    def __init__(self, texts: list[bytes], lower: bool = False):
        joined = b" " + b" ".join(texts) + b" "
        if lower:
            joined = joined.lower()
        raw = np.frombuffer(joined, dtype=np.uint8)
        space = _SPACE[raw]
        self.buffer = np.where(space, np.uint8(32), raw)  # borders of a word look alike whatever the white space
        edge = np.diff(np.concatenate([[True], space]).astype(np.int8))
        self.start = np.flatnonzero(edge == -1)
        self.end = np.flatnonzero(edge == 1)
        lengths = np.array([len(t) + 1 for t in texts], dtype=np.int64)
        bounds = 1 + lengths.cumsum()
        at = np.searchsorted(self.start, bounds)
        self.sizes = np.diff(np.concatenate([[0], at]))
        self.doc = np.repeat(np.arange(len(texts)), self.sizes)
        n = len(self.buffer)
        self._sum = np.concatenate([np.zeros(1, dtype=np.uint64), (_BYTE[self.buffer] * _powers(_BASE, n)).cumsum(dtype=np.uint64)])
        self._undo = _powers(_INVERSE, n)

    def hashes(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """64-bit hashes of byte ranges; they depend on the bytes alone."""
        return mix((self._sum[end] - self._sum[start]) * self._undo[start])

    def word_hashes(self) -> np.ndarray:
        return self.hashes(self.start, self.end)

    def distinct(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(first word number, hash) of each distinct word, and each word's number among them."""
        h = self.word_hashes()
        values, first, back = np.unique(h, return_index=True, return_inverse=True)
        return first, values, back

    def grams(self, words: np.ndarray, lengths: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
        """(position in ``words``, hash) of byte n-grams of the chosen words, each word bordered by its white space."""
        owner, found = [], []
        low = np.maximum(self.start[words] - 1, 0)
        high = self.end[words] + 1
        for n in lengths:
            count = np.maximum(high - low - n + 1, 0)
            own = np.repeat(np.arange(len(words)), count)
            at = np.arange(len(own)) - np.repeat(count.cumsum() - count, count) + low[own]
            owner.append(own)
            found.append(mix(self.hashes(at, at + n) + np.uint64(n)))
        return np.concatenate(owner), np.concatenate(found)


def sums_by(owner: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """Row sums of ``values`` (rows x columns) by owner, as n x columns."""
    return np.stack([np.bincount(owner, values[:, k], n) for k in range(values.shape[1])], axis=1)
