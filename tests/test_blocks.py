"""The blocks of many trajectories against the kernel one by one, and their pieces against brute force."""

import itertools

import numpy as np
import pytest

from pointveil.config import Cfg
from pointveil.plans.batch import Blocks, best_paths
from pointveil.plans.kernel import Kernel, viterbi
from tests.test_kernels import city

SETTINGS = [
    {}, {"n": 1}, {"n": 3}, {"overlap": False}, {"mbr": False}, {"fill": "chain"}, {"theta": "slot"}, {"theta": "inf", "speed_kmh": 1e6},
    {"delta_mode": "unit"}, {"eps_mode": "per_draw"}, {"speed_kmh": 0.5}, {"metric": "space"},
]


@pytest.mark.parametrize("method", ["hier", "flat", "geo_only", "indep_reach", "indep_free"])
@pytest.mark.parametrize("changes", SETTINGS, ids=str)
def test_blocks_give_the_rows_of_the_kernel(method, changes):
    k, cfg = city(30), Cfg(seed="7", **changes)
    kernel, rng = Kernel(k, cfg), np.random.default_rng(1)
    for length, eps in ((1, None), (2, 3.0), (3, None), (6, None)):
        ids = [f"t{length}.{i}" for i in range(20)]
        pois = rng.integers(0, 30, (20, length))
        t = np.sort(np.stack([rng.choice(144, length, replace=False) for _ in ids]), axis=1)
        got = list(Blocks(Kernel(k, cfg)).run(method, ids, pois, t, eps))
        assert [i for b in got for i in b.ids] == ids
        rows = [(b, i) for b in got for i in range(len(b.ids))]
        for (b, i), one, p, s in zip(rows, ids, pois.tolist(), t.tolist()):
            want = kernel.run(method, one, [k.poi_ids[x] for x in p], s, eps)
            assert [k.poi_ids[x] for x in b.poi[i]] == want["poi"] and b.t[i].tolist() == want["t"]
            assert (bool(b.smoothed[i]), int(b.attempts[i]), bool(b.connected[i])) == (want["smoothed"], want["attempts"], want["connected"])
            assert [(a, c, g[i].tolist()) for a, c, g in b.z] == [(a, c, [int(x) for x in g]) for a, c, g in want["z"]]


@pytest.mark.parametrize("nodes,share", [(9, 0.5), (60, 0.5), (300, 0.5), (300, 0.02)])
def test_best_paths_are_the_kernels_or_left_to_it(nodes, share):
    rng = np.random.default_rng(nodes)
    edge = rng.random((nodes, nodes)) < share
    error = rng.integers(0, 12, (25, 4, nodes)).astype(float)  # many ties
    error[rng.random(error.shape) < 0.1] = np.inf
    path, sure = best_paths(error.copy(), lambda i, rows, before, after: edge[before, after])
    assert sure.any() or share < 0.1
    for row in sure.nonzero()[0]:
        assert path[row].tolist() == viterbi(error[row], edge)[0]


def test_paths_without_a_completion_are_known():
    k = city(8)
    kernel, rng = Kernel(k, Cfg(speed_kmh=1.0)), np.random.default_rng(0)
    k.open_slots[:] = rng.random(k.open_slots.shape) < 0.3
    found = set()
    for _ in range(60):
        path = [int(rng.integers(4)) * 24 + h for h in np.sort(rng.integers(8, 10, 3))]
        spots = [[(p, s) for p in k.region_members[r] for s in k.region_slots[r]] for r in path]
        some = any(kernel.feasible([p for p, _ in x], [s for _, s in x]) for x in itertools.product(*spots))
        assert kernel._possible(path) == some
        found.add(some)
    assert found == {True, False}


def test_fill_is_uniform_over_the_completions():
    k = city(8)
    kernel, path = Kernel(k, Cfg(seed="7", speed_kmh=12.0)), [8, 24 + 8]
    spots = [[(int(p), int(s)) for p in k.region_members[r] for s in k.region_slots[r]] for r in path]
    all_ = [x for x in itertools.product(*spots) if kernel.feasible([p for p, _ in x], [s for _, s in x])]
    n = 100 * len(all_)
    p, t, smoothed, attempts = kernel.fills([f"t{i}" for i in range(n)], np.tile(path, (n, 1)))
    ok = ~smoothed
    assert len(all_) > 10 and ok.mean() > 0.99 and attempts.min() >= 1
    seen = [tuple(zip(a, b)) for a, b in zip(p[ok].tolist(), t[ok].tolist())]
    counts = np.unique([all_.index(x) for x in seen], return_counts=True)[1]
    assert counts.sum() == ok.sum() and len(counts) == len(all_)
    expected = ok.sum() / len(all_)
    assert ((counts - expected) ** 2 / expected).sum() < len(all_) + 5 * np.sqrt(2 * len(all_))


def test_hard_fills_have_the_law_of_trying(monkeypatch):
    from pointveil.plans import kernel as module

    monkeypatch.setattr(module, "FIRST_TRIES", ())
    monkeypatch.setattr(module, "COUNT_CELLS", 1 << 12)
    k = city(8)
    k.open_slots[:] = np.random.default_rng(1).random(k.open_slots.shape) < 0.4
    k.region_members[24 + 8] = k.region_members[24 + 8][:1]  # lists of several lengths
    for path in ([8, 24 + 8], [8, 48 + 8, 24 + 8]):
        kernel = Kernel(k, Cfg(seed="7", speed_kmh=8.0, gamma=100))
        spots = [[(int(p), int(s)) for p in k.region_members[r] for s in k.region_slots[r]] for r in path]
        every = list(itertools.product(*spots))
        all_ = [x for x in every if kernel.feasible([p for p, _ in x], [s for _, s in x])]
        n, share = 4000, len(all_) / len(every)
        others = [8] * (len(path) - 1) + [32 + 8]  # rows of other sizes beside
        p, t, smoothed, attempts = kernel.fills([f"t{i}" for i in range(n)], np.array([path if i % 8 else others for i in range(n)]))
        mine = np.arange(n) % 8 > 0
        most = min(len(every), 100)
        failed = (1 - share) ** most
        assert abs(smoothed[mine].mean() - failed) < 0.02
        ok = mine & ~smoothed
        mean = sum(i * share * (1 - share) ** (i - 1) for i in range(1, most + 1)) / (1 - failed)
        assert abs(attempts[ok].mean() / mean - 1) < 0.1
        seen = [all_.index(tuple(zip(a, b))) for a, b in zip(p[ok].tolist(), t[ok].tolist())]
        counts = np.bincount(seen, minlength=len(all_))
        expected = ok.sum() / len(all_)
        assert ((counts - expected) ** 2 / expected).sum() < len(all_) + 5 * np.sqrt(2 * len(all_))


def test_hard_fills_are_not_tried_thousands_of_times(monkeypatch):
    from pointveil.plans import kernel as module

    numbers, mixed = [], module._below
    monkeypatch.setattr(module, "_below", lambda x, n: numbers.append(len(x)) or mixed(x, n))
    k = city(8)
    k.open_slots[:, 52:] = False  # the slots of one hour must rise in its first four
    path = [8, 24 + 8, 48 + 8, 72 + 8]
    kernel = Kernel(k, Cfg(seed="7", speed_kmh=100.0))
    _, _, smoothed, attempts = kernel.fills([f"t{i}" for i in range(50)], np.tile(path, (50, 1)))
    assert (attempts[~smoothed] > 200).any() and sum(numbers) < 50 * 2000


def test_people_are_made_in_many_tasks(spark):
    from pyspark.sql import functions as F

    from pointveil.operators import synth

    people = spark.range(200).select(F.col("id").alias("person")).coalesce(1)
    k, cfg = city(), Cfg(seed="7")
    made = synth.panel(people, k, np.ones((12, 24)), np.array([30.0, 60.0]), cfg)
    assert made.select(F.spark_partition_id().alias("task")).distinct().count() > spark.sparkContext.defaultParallelism
    assert made.select("traj_id").distinct().count() == 200
