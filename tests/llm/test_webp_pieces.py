"""Pieces of the WebP store against their plain forms."""

import numpy as np
import pytest

from pointveil.llm.webp import features
from pointveil.llm.webp_read import decode
from pointveil.llm.webp_write import _N_LOG_N, _costs, _last_equal, _runs, encode


def test_runs_tell_the_lengths_again():
    rng = np.random.default_rng(0)
    for _ in range(300):
        lengths = np.repeat(rng.integers(0, 12, 60) * (rng.random(60) < 0.6), rng.choice([1, 1, 2, 3, 4, 5, 7, 12, 150], 60))
        lengths = np.append(lengths, 10)  # a length of 10 is the byte of a line end
        symbols, bits, sizes = _runs(np.append(lengths, np.zeros(5, dtype=np.int64)))
        out: list[int] = []
        for s, more, n in zip(symbols, bits, sizes):
            out += [s] if s < 16 else [out[-1]] * (3 + more) if s == 16 else [0] * ((3 if s == 17 else 11) + more)
            assert n == {16: 2, 17: 3, 18: 7}.get(s, 0)
        assert out == lengths.tolist() and len(symbols) < len(lengths)


def test_last_equal_of_large_words():
    words = np.random.default_rng(1).choice(np.array([0, 1, 2**31, 2**32 - 1], dtype=np.uint32), 500)
    for i, last in enumerate(_last_equal(words).tolist()):
        before = (words[:i] == words[i]).nonzero()[0]
        assert last == (before[-1] if len(before) else -1)


@pytest.mark.parametrize("size", [40, len(_N_LOG_N) + 10])
def test_costs_of_many_parts_are_those_of_each(size):
    rng = np.random.default_rng(2)
    parts = [rng.integers(0, top, n).astype(np.uint8) for top, n in ((3, size), (256, size - 4), (90, 33))]
    for part, cost in zip(parts, _costs(parts)):
        share = np.unique(part, return_counts=True)[1] / len(part)
        assert cost == pytest.approx(-len(part) * float((share * np.log2(share)).sum()), abs=1e-6)


@pytest.mark.parametrize("shape", [(4, 16), (42, 16), (3, 5), (1, 1), (7, 32)])
def test_features_and_pixels_of_any_shape(shape):
    pixels = np.random.default_rng(3).integers(0, 256, (*shape, 4)).astype(np.uint8)
    assert (decode(encode(pixels, cache=8, refs=True)) == pixels).all()
    told = features(pixels).split(";")
    assert told[0] == f"{shape[1]}x{shape[0]}" and told[1] == ",".join(f"{m:.3f}" for m in pixels.reshape(-1, 4).mean(axis=0))
    flat = np.pad(pixels.ravel(), (0, max(0, 64 - pixels.size)))
    cut = len(flat) * np.arange(65) // 64
    cells = np.array([flat[a:b].mean() for a, b in zip(cut, cut[1:])])
    assert told[2] == np.packbits(cells > flat.mean()).tobytes().hex()
