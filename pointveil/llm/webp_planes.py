"""Lossless WebP: fixed values of the format and the four transforms, forwards and back."""

from __future__ import annotations

import functools

import numpy as np

# Fixed values of the format: order of code-length codes, and the first 120 plane distances as (x, y) offsets.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3),
    (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0),
    (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2), (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5), (8, 0), (4, 7), (-4, 7), (7, 4),
    (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
CACHE_FACTOR = 0x1E35A7BD
SIGNATURE, GREEN, LENGTHS, DISTANCES, MOST_SIDE = 0x2F, 256, 24, 40, 1 << 14


@functools.lru_cache(maxsize=16)
def reversed_bits(n: int) -> np.ndarray:
    """The numbers below 2**n with their n bits in the other order."""
    out = np.zeros(1, dtype=np.int64)
    for _ in range(n):
        out = np.concatenate([2 * out, 2 * out + 1])
    return out


@functools.lru_cache(maxsize=8)
def reversed_few(n: int) -> list[int]:
    """``reversed_bits`` of a short code as a list."""
    return reversed_bits(n).tolist()


def channels(argb: np.ndarray) -> list[np.ndarray]:
    """A, R, G, B of every word."""
    parts = argb.astype("<u4", copy=False).view(np.uint8).reshape(-1, 4).astype(np.int32)
    return [parts[:, 3], parts[:, 2], parts[:, 1], parts[:, 0]]


def joined(a, r, g, b) -> np.ndarray:
    """Words of four channels, each taken modulo 256."""
    n = max(np.size(c) for c in (a, r, g, b))
    parts = np.empty((n, 4), dtype=np.uint8)
    for k, c in enumerate((b, g, r, a)):
        parts[:, k] = np.asarray(c) & 255
    return parts.view("<u4").ravel()


def _guess(mode: int, left: int, top: int, corner: int, right: int) -> int:
    """The predictor's value of a pixel (ARGB words)."""

    def by_byte(f, *words):
        return sum(f(*[w >> s & 255 for w in words]) << s for s in (0, 8, 16, 24))

    def mean(x, y):
        return by_byte(lambda a, b: (a + b) >> 1, x, y)

    def clip(v):
        return min(255, max(0, v))

    if mode == 0 or mode > 13:
        return 0xFF000000
    if mode == 11:
        near_left = near_top = 0
        for s in (0, 8, 16, 24):
            x, y, c = left >> s & 255, top >> s & 255, corner >> s & 255
            near_left += abs(y - c)  # |x + y - c - x|
            near_top += abs(x - c)
        return left if near_left < near_top else top
    if mode == 12:
        return by_byte(lambda x, y, c: clip(x + y - c), left, top, corner)
    if mode == 13:
        def half(m, c):
            d = m - c
            return clip(m + (d // 2 if d >= 0 else -(-d // 2)))

        return by_byte(half, mean(left, top), corner)
    choices = {
        1: lambda: left, 2: lambda: top, 3: lambda: right, 4: lambda: corner,
        5: lambda: mean(mean(left, right), top), 6: lambda: mean(left, corner), 7: lambda: mean(left, top),
        8: lambda: mean(corner, top), 9: lambda: mean(top, right), 10: lambda: mean(mean(left, corner), mean(top, right)),
    }
    return choices[mode]()


def _around(out, i: int, x: int, y: int, width: int, mode: int) -> int:
    if y == 0:
        return 0xFF000000 if x == 0 else int(out[i - 1])
    if x == 0:
        return int(out[i - width])
    return _guess(mode, int(out[i - 1]), int(out[i - width]), int(out[i - width - 1]), int(out[i - width + 1]))


def _byte_sum(x: int, y: int, sign: int = 1) -> int:
    return sum(((x >> s & 255) + sign * (y >> s & 255) & 255) << s for s in (0, 8, 16, 24))


def predict(argb: np.ndarray, width: int, block: int, modes: np.ndarray, undo: bool) -> np.ndarray:
    """Add (undo) or take off the predictor's values; where all blocks look left, or all up, by whole rows and columns."""
    height, across = len(argb) // width, -(-width >> block)
    kinds = (modes >> np.uint32(8)) & np.uint32(15)
    plain = next((m for m in (1, 2) if (kinds == m).all()), None)
    if plain and undo:
        c = np.stack(channels(argb)).reshape(4, height, width)
        c[0, 0, 0] += 255
        if plain == 2:
            c[:, 0] = c[:, 0].cumsum(axis=1)
        else:
            c[:, :, 0] = c[:, :, 0].cumsum(axis=1)
        return joined(*(c.cumsum(axis=3 - plain) & 255).reshape(4, -1))
    if plain:
        c = np.stack(channels(argb)).reshape(4, height, width)
        guess = np.zeros_like(c)
        guess[0, 0, 0] = 255
        guess[:, 1:, 0], guess[:, 0, 1:] = c[:, :-1, 0], c[:, 0, :-1]
        guess[:, 1:, 1:] = c[:, :-1, 1:] if plain == 2 else c[:, 1:, :-1]
        return joined(*(c - guess & 255).reshape(4, -1))
    source, out = (None, argb.copy()) if undo else (argb, np.zeros_like(argb))
    for i in range(len(argb)):
        y, x = divmod(i, width)
        mode = int(kinds[(y >> block) * across + (x >> block)])
        guess = _around(out if undo else source, i, x, y, width, mode)
        out[i] = _byte_sum(int(argb[i]), guess, 1 if undo else -1)
    return out


def cross(argb: np.ndarray, width: int, block: int, factors: np.ndarray, undo: bool) -> np.ndarray:
    a, r, g, b = channels(argb)
    y, x = np.divmod(np.arange(len(argb)), width)
    f = factors[(y >> block) * -(-width >> block) + (x >> block)]

    def signed(v):
        return (v.astype(np.int32) & 255) - ((v.astype(np.int32) & 128) << 1)

    red_blue, green_blue, green_red = (signed(f >> np.uint32(s)) for s in (16, 8, 0))
    sign = 1 if undo else -1
    red = r + sign * (green_red * signed(g) >> 5) & 255
    blue = b + sign * (green_blue * signed(g) >> 5) + sign * (red_blue * signed(red if undo else r) >> 5)
    return joined(a, red, g, blue)


def pack_bits(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0
