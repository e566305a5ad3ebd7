"""The near-duplicate stage of the pipeline against exact five-word Jaccard similarity."""

import numpy as np
import pyarrow as pa

import corpus_pipeline as cp
from pointveil.llm import simhash
from pointveil.llm.simhash import KEYS, LOOSE_DISTANCE, GrayIndex, alike_groups, alike_roots, forest, gray_rank, key_hashes, shingle_hashes, wide_fingerprints
from tests.llm.test_pipeline import edited, table, text


def shingles(t):
    return set(shingle_hashes(t.encode(), 5))


def brute(sets):
    near = np.array([[10 * len(a & b) >= 8 * len(a | b) for b in sets] for a in sets])
    root = list(range(len(sets)))
    for _ in sets:
        root = [min(root[j] for j in np.flatnonzero(near[i])) for i in range(len(sets))]
    return root


def cut(t, k):
    """The text with its last ``k`` words replaced: k of n shingles change on either side."""
    words = t.split()
    return " ".join(words[: len(words) - k] + [f"new{i}" for i in range(k)])


def test_groups_are_those_of_exact_similarity(spark):
    base = [text(300 + i, 120) for i in range(8)]
    texts = [edited(b, s, k) for b in base for s, k in enumerate((0, 1, 2, 3, 4, 6, 9))]
    # 204 words have 200 shingles: 22 changed give 178 / 222 = 0.802, 23 give 177 / 223 = 0.794
    texts += [t for i in range(60) for b in [text(900 + i, 204)] for t in (b, cut(b, 22 + i % 2))]
    want = brute([shingles(t) for t in texts])
    for hot, most in ((20_000, 1 << 26), (4, 4000)):  # small bounds: keys and groups are compared chunk by chunk
        got = {r.node: r.root for r in alike_groups(table(spark, texts), hot=hot, most=most).collect()}
        assert [got.get(i, i) for i in range(len(texts))] == want
    kept = {r.doc_id for r in cp.near_stage(spark, table(spark, texts), "").collect()}
    assert kept == set(want)


def test_roots_match_brute_force():
    rng = np.random.default_rng(5)
    for size in (1, 2, 4, 9, 40, 200):
        base = [rng.integers(0, 1 << 60, size) for _ in range(5)]
        sets = []
        for _ in range(60):
            s = base[rng.integers(5)].copy()
            swap = rng.random(size) < rng.choice([0, 0.05, 0.1, 0.12, 0.2])
            s[swap] = rng.integers(0, 1 << 60, swap.sum())
            sets.append(np.unique(s[rng.random(size) < 0.97] if size > 9 else s).astype(np.uint64))
        want = brute([set(s.tolist()) for s in sets])
        assert alike_roots(sets).tolist() == want


def test_pairs_at_the_bound_are_candidates():
    for words, changed in ((10, 0), (13, 1), (24, 2), (204, 22)):
        a = [text(i, words) for i in range(1500)]
        b = [cut(t, changed) if changed else t for t in a]
        a, b = [t.encode() for t in a], [t.encode() for t in b]
        shared = (key_hashes(a) == key_hashes(b)).any(axis=1)
        apart = np.bitwise_count(wide_fingerprints(a) ^ wide_fingerprints(b)).sum(axis=1)
        assert key_hashes(a).shape == (1500, KEYS)
        assert (shared & (apart <= LOOSE_DISTANCE)).all()


def test_gray_index_over_wide_fingerprints_matches_brute_force():
    rng = np.random.default_rng(9)
    base = rng.integers(0, 1 << 63, (12, 4), dtype=np.uint64) * np.uint64(2) + rng.integers(0, 2, (12, 4), dtype=np.uint64)
    fps = base[rng.integers(12, size=300)]
    for row in fps:  # up to 60 of 256 bits turned
        for bit in rng.choice(256, rng.integers(60), replace=False):
            row[bit // 64] ^= np.uint64(1) << np.uint64(bit % 64)
    group = rng.integers(0, 3, 300)
    apart = np.bitwise_count(fps[:, None] ^ fps[None]).sum(axis=2)
    for distance in (0, 20, LOOSE_DISTANCE):
        want = {(i, j) for i, j in zip(*np.nonzero((apart <= distance) & (group[:, None] == group))) if i < j}
        index = GrayIndex(group, fps)
        assert {(min(a, b), max(a, b)) for x, y in index.links(distance, closure=False) for a, b in zip(x.tolist(), y.tolist())} == want
        root = forest(300, iter([tuple(np.array(sorted(want), dtype=np.int64).reshape(-1, 2).T)]))
        assert (forest(300, index.links(distance)) == root).all()
    ranks = [tuple(int(w) for w in r) for r in gray_rank(fps)]
    word = sum(fps[:, k].astype(object) << (64 * (3 - k)) for k in range(4))
    for s in (1, 2, 4, 8, 16, 32, 64, 128):
        word = word ^ (word >> s)
    assert ranks == [tuple((w >> (64 * (3 - k))) & ((1 << 64) - 1) for k in range(4)) for w in word.tolist()]


def test_candidates_are_found_by_the_gray_index(monkeypatch):
    a, b = text(1, 204), text(2, 204)
    texts = [t.encode() for t in (a, cut(a, 5), b, cut(b, 22), text(3, 204))]
    fps = wide_fingerprints(texts).view(np.int64)
    rows = pa.table({"key": [1, 1, 1, 1, 2], "id": [10, 11, 12, 13, 14], **{f: fps[:, k] for k, f in enumerate(simhash.WIDE)}})
    edges = simhash._loose_edges(LOOSE_DISTANCE)
    assert edges(rows).to_pydict() == {"a": [10, 12], "b": [11, 13]}
    assert edges(rows.slice(4)).num_rows == 0
    monkeypatch.setattr(GrayIndex, "links", lambda *a, **k: iter([]))
    assert edges(rows).num_rows == 0
