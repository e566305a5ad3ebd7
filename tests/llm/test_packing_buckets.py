"""Bucket bounds where there are as many buckets as lengths, or more."""

import random

from pointveil.llm.packing import optimal_boundaries
from tests.llm.test_dedup_packing import plain_padding


def test_rounds_without_gain_keep_the_earlier_cut():
    assert optimal_boundaries({0: 1, 1: 1, 2: 1}, 8) == [1, 2]
    rnd = random.Random(2)
    for _ in range(200):
        hist = {rnd.randint(0, 6): rnd.randint(1, 9) for _ in range(rnd.randint(1, 7))}
        k = rnd.randint(1, 8)
        bounds = optimal_boundaries(hist, k)
        pad = sum(n * (min(b for b in bounds if b >= v) - v) for v, n in hist.items())
        assert len(bounds) <= k and pad == plain_padding(hist, k), hist
