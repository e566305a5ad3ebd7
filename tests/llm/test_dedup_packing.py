"""Exact and near duplicates and packing against brute force."""

import hashlib
import itertools
import random

import numpy as np
import xxhash
from pyspark.sql import functions as F

from pointveil.llm.components import components
from pointveil.llm.exact_dedup import dedup
from pointveil.llm.packing import optimal_boundaries, pack
from pointveil.llm.simhash import GrayIndex, chunked, crowded, forest, linked, near_duplicates

SCHEMA = "doc_id long, text string, key long, name string, block string, root string"


def frame(spark, texts):
    return spark.createDataFrame([(i, t, 7, "x", "y", "z") for i, t in enumerate(texts)], SCHEMA)


def corpus():
    rnd = random.Random(4)
    words = ["alpha", "Beta", "gamma", "ünï", "x"]
    texts = [None, "", " ", "a"] + [" ".join(rnd.choices(words, k=rnd.choice([1, 2, 3, 9, 60]))) for _ in range(60)]
    return texts + ["long " * 9000, "long " * 9000, "long " * 8999 + "lonG "] + texts[10:30] + [texts[5]] * 40


def test_exact_dedup_matches_grouping(spark):
    texts = corpus()
    for size, key in ((4096, F.xxhash64), (7, F.xxhash64), (7, lambda b: F.length(b).cast("long") % 3)):
        got = {r.doc_id: r for r in dedup(frame(spark, texts), size, key).collect()}
        groups = {}
        for i, t in enumerate(texts):
            groups.setdefault(t or "", []).append(i)
        assert len(got) == len(texts)
        for i, t in enumerate(texts):
            g = groups[t or ""]
            r = got[i]
            assert (r.keep_id, r.group_size, r.kept) == (max(g), len(g), i == max(g))
            assert r.text_sha256 == hashlib.sha256((t or "").encode()).hexdigest()


def test_exact_dedup_repeated_and_null_ids(spark):
    df = spark.createDataFrame([(1, "a"), (1, "a"), (None, "a"), (2, "b")], "doc_id long, text string")
    rows = dedup(df).collect()
    assert len(rows) == 4 and sum(r.kept for r in rows) == 2
    assert dedup(df.limit(0)).count() == 0


def plain_fingerprint(text, width):
    words = [w.decode() for w in (text or "").encode().lower().split()]
    runs = [words] if 0 < len(words) < width else [words[i : i + width] for i in range(len(words) - width + 1)]
    hashes = [xxhash.xxh64_intdigest(" ".join(r), 42) for r in runs if r]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(fps, distance):
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(fps)), 2):
        if (fps[i] ^ fps[j]).bit_count() <= distance:
            a, b = sorted((find(i), find(j)))
            root[b] = a
    return [find(i) for i in range(len(fps))]


def test_near_duplicates_match_brute_force(spark):
    texts = corpus()
    base = " ".join(f"word{i}" for i in range(400))
    texts += [base] + [base.replace(f"word{i} ", "other ") for i in range(0, 400, 9)]
    fps = [plain_fingerprint(t, 3) for t in texts]
    want = plain_components(fps, 3)
    for hot in (20_000, 5):
        got = {r.doc_id: r for r in near_duplicates(frame(spark, texts), hot=hot).collect()}
        assert [got[i].fingerprint for i in range(len(texts))] == [f"{f:016x}" for f in fps]
        assert [got[i].component_id for i in range(len(texts))] == want
    assert near_duplicates(frame(spark, texts).limit(0)).count() == 0


def test_gray_index_closure_is_exact():
    rng = np.random.default_rng(3)
    centre = rng.integers(0, 1 << 62, 30, dtype=np.uint64)
    fps = set()
    for c in centre.tolist():
        for _ in range(40):
            x = c
            for b in rng.integers(0, 64, rng.integers(0, 5)).tolist():
                x ^= 1 << b
            fps.add(x)
    fps = sorted(fps)
    arr = np.array(fps, dtype=np.uint64)
    for distance in (0, 1, 3, 6):
        root = forest(len(arr), GrayIndex(np.zeros(len(arr), dtype=np.int64), arr).links(distance))
        assert root.tolist() == plain_components(fps, distance)


def test_dense_ball_is_tied_without_pairs(spark):
    fps = [(1 << a) | (1 << b) for a, b in itertools.combinations(range(0, 64, 3), 2)]
    want = plain_components(fps, 3)
    df = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for f in fps], "fp long")
    for hot in (10**6, 20):
        got = linked(df, 3, hot).collect()
        assert len(got) == len(fps) and len({r.root for r in got}) == len(set(want))


def test_chunks_bound_a_key_and_lose_no_pair(spark):
    rows = spark.createDataFrame([(7, f) for f in range(60)] + [(8, f) for f in range(3)], "key long, fp long")
    keys = {}
    for r in chunked(rows, crowded(rows, 20), ["fp"]).collect():
        keys.setdefault(r.key, set()).add(r.fp)
    assert keys.pop(8) == {0, 1, 2} and max(map(len, keys.values())) < 40
    assert {p for v in keys.values() for p in itertools.combinations(sorted(v), 2)} == set(itertools.combinations(range(60), 2))


def test_components_of_chains_stars_and_none(spark):
    edges = [(i, i + 1) for i in range(0, 60)] + [(100, i) for i in range(101, 150)] + [(5, 5), (3, 2), (2, 3)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and all(got[i] == 100 for i in range(100, 150))
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def plain_padding(hist, k):
    lens = sorted(hist)
    best = None
    for r in range(1, min(k, len(lens)) + 1):
        for cut in itertools.combinations(lens[:-1], r - 1):
            bounds = [max(1, b) for b in (*cut, lens[-1])]
            pad = sum(n * (min(b for b in bounds if b >= v) - v) for v, n in hist.items())
            best = pad if best is None else min(best, pad)
    return best


def test_boundaries_are_optimal():
    rnd = random.Random(1)
    for _ in range(60):
        hist = {rnd.randint(0, 40): rnd.randint(1, 9) for _ in range(rnd.randint(1, 9))}
        k = rnd.randint(1, 4)
        bounds = optimal_boundaries(hist, k)
        pad = sum(n * (min(b for b in bounds if b >= v) - v) for v, n in hist.items())
        assert len(bounds) <= k and pad == plain_padding(hist, k)


def test_pack_keeps_every_token_and_the_budget(spark):
    texts = corpus()
    rows = pack(frame(spark, texts), max_len=50, buckets=4, budget=200).collect()
    tokens = {}
    for r in rows:
        tokens[r.doc_id] = tokens.get(r.doc_id, 0) + r.n_tokens
        assert 0 <= r.n_tokens <= r.bucket_len and r.padding == r.bucket_len - r.n_tokens
    assert tokens == {i: len((t or "").encode().split()) for i, t in enumerate(texts)}
    batches = {}
    for r in rows:
        batches.setdefault(r.batch_id, []).append(r.slot)
    for b, slots in batches.items():
        bound = int(b.split("-")[0])
        assert sorted(slots) == list(range(len(slots))) and bound * len(slots) <= max(200, bound)
    part = {b: len(s) for b, s in batches.items() if len(s) < max(1, 200 // int(b.split("-")[0]))}
    assert len({b.split("-")[0] for b in part}) == len(part)
    assert pack(frame(spark, texts).limit(0)).count() == 0
