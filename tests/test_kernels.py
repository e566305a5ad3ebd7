"""Kernels against enumeration, worked examples and invariants; no Spark needed."""

import itertools
import math

import numpy as np
import pytest

from pointveil.config import Cfg
from pointveil.functions.distance import category_value
from pointveil.functions.rng import draw
from pointveil.operators import cost
from pointveil.operators.budget import split_value
from pointveil.operators.expmech import sensitivity, tail_bound
from pointveil.plans.kernel import Chain, Kernel, pick, smooth, viterbi, windows_of
from pointveil.plans.knowledge import Knowledge, haversine_matrix


def toy(n=7, seed=1):
    rng = np.random.default_rng(seed)
    p = rng.random((n, 2)) * 5
    d = np.sqrt(((p[:, None] - p) ** 2).sum(axis=2))
    a = rng.random((n, n)) < 0.6
    np.fill_diagonal(a, True)
    return d, a


def paths(a, n):
    return [p for p in itertools.product(range(len(a)), repeat=n) if all(a[x, y] for x, y in zip(p, p[1:]))]


def law(d, a, gram, eps, delta):
    out = {p: math.exp(-eps * sum(d[g, x] for g, x in zip(gram, p)) / (2 * delta)) for p in paths(a, len(gram))}
    total = sum(out.values())
    return {p: w / total for p, w in out.items()}


def test_chain_law_equals_the_enumerated_law():
    d, a = toy()
    chain = Chain(d, a.astype(float))
    for gram, eps in (((0, 1, 2), 1.0), ((3, 3), 5.0), ((4,), 2.0)):
        want = law(d, a, gram, eps, 3 * d.max())
        m = chain.messages(gram, eps, 3 * d.max())
        for p, w in want.items():
            got = m[0][p[0]] / m[0].sum()
            for i in range(1, len(gram)):
                row = m[i] * a[p[i - 1]]
                got *= row[p[i]] / row.sum()
            assert got == pytest.approx(w, abs=1e-12)


def test_chain_samples_follow_the_law():
    d, a = toy(5)
    chain, want = Chain(d, a.astype(float)), law(*toy(5), (0, 1), 8.0, 2.0)
    seen = {}
    n = 20_000
    for i in range(n):
        p = tuple(chain.sample((0, 1), 8.0, 2.0, [draw("s", i, 0), draw("s", i, 1)]))
        seen[p] = seen.get(p, 0) + 1
    assert set(seen) <= set(want)
    chi = sum((seen.get(p, 0) - n * w) ** 2 / (n * w) for p, w in want.items())
    assert chi < len(want) + 5 * math.sqrt(2 * len(want))


def test_worst_ratio_keeps_the_bound_for_all_inputs():
    d, a = toy()
    for eps in (0.5, 1.0, 3.0):
        laws = [law(d, a, g, eps, sensitivity(2, d.max())) for g in paths(a, 2)]
        worst = max(max(x[p] for x in laws) / min(x[p] for x in laws) for p in laws[0])
        assert worst <= math.exp(eps) * (1 + 1e-9)


def test_tail_bound_holds():
    d, a = toy()
    for zeta in (0.5, 1.0, 2.0):
        bound = tail_bound(2.0, 2 * d.max(), len(paths(a, 2)), zeta)
        for g in paths(a, 2)[:5]:
            mass = sum(w for p, w in law(d, a, g, 2.0, 2 * d.max()).items() if sum(d[x, y] for x, y in zip(g, p)) > bound)
            assert mass <= math.exp(-zeta)


@pytest.mark.parametrize("length", [1, 2, 3, 4])
def test_viterbi_is_the_optimum(length):
    for seed in range(12):
        rng = np.random.default_rng(seed)
        _, a = toy(6, seed)
        node = rng.random((length, 6))
        got = viterbi(node, a)
        def value(p):
            if length == 1:
                return node[0][p[0]]
            return sum(node[i][p[i]] + node[i + 1][p[i + 1]] for i in range(length - 1))
        options = [value(p) for p in paths(a, length)]
        if not options:
            assert got is None
        else:
            assert got[1] == pytest.approx(min(options)) and value(got[0]) == pytest.approx(min(options))


def test_windows_cover_every_position_n_times():
    assert sorted(windows_of(4, 2)) == [(0, 0), (0, 1), (1, 2), (2, 3), (3, 3)]
    for length in range(1, 11):
        for n in (1, 2, 3):
            w = windows_of(length, n)
            m = min(n, length)
            assert len(w) == length + m - 1
            assert all(sum(a <= i <= b for a, b in w) == m for i in range(length))
            assert split_value(length, Cfg(n=n), "hier") * len(w) == pytest.approx(5.0)
    assert windows_of(5, 2, overlap=False) == [(0, 1), (2, 3), (4, 4)]


def test_category_distances():
    assert category_value("a/0/1", "a/0/1") == 0 and category_value("a", "b") == 10
    assert category_value("a/0/1", "a/0/2") == 2 and category_value("a/0/1", "a/1/2") == 5
    assert all(category_value(x, y) == category_value(y, x) for x, y in itertools.product(["a", "a/0", "a/0/1", "a/1/2", "b/0"], repeat=2))


def test_search_space_worked_example():
    assert cost.search_space(1000, 5, 15, 0.2) == pytest.approx(9.77985e19, rel=2e-3)
    assert cost.search_space(10**9, 40, 1) == math.inf


def city(n=12, regions=4):
    rng = np.random.default_rng(0)
    lat, lon = 40.7 + rng.random(n) * 0.05, -74 + rng.random(n) * 0.05
    km = haversine_matrix(lat, lon)
    k = Knowledge([f"p{i:02d}" for i in range(n)], lat, lon, np.ones((n, 144), dtype=bool), km, (np.arange(n)[:, None] % 3 != np.arange(n) % 3) * 10.0, np.ones(n))
    k.region_members = [np.arange(n)[np.arange(n) % regions == r] for r in range(regions) for _ in range(24)]
    k.region_slots = [np.arange(h * 6, h * 6 + 6) for _ in range(regions) for h in range(24)]
    k.encode = np.array([[(p % regions) * 24 + h for h in range(24)] for p in range(n)])
    t = np.tile(np.arange(24) + 0.5, regions)
    g = np.repeat(np.arange(regions), 24)
    k.D = np.sqrt(np.minimum(np.abs(t[:, None] - t), 12) ** 2 + (g[:, None] != g) * 4.0)
    k.diameter = float(k.D.max())
    k.A = t[None, :] >= t[:, None]
    k.box = np.array([[lat[m].min(), lat[m].max(), lon[m].min(), lon[m].max()] for m in k.region_members])
    return k


@pytest.mark.parametrize("method", ["hier", "flat", "geo_only", "indep_reach", "indep_free"])
def test_methods_give_feasible_trajectories_and_repeat_themselves(method):
    k, cfg = city(), Cfg(n=2)
    kernel = Kernel(k, cfg)
    for i in range(25):
        rng = np.random.default_rng(i)
        length = int(rng.integers(1, 7))
        pois = [k.poi_ids[j] for j in rng.integers(0, 12, length)]
        t = sorted(rng.choice(144, length, replace=False).tolist())
        r = kernel.run(method, f"t{i}", pois, t)
        out = [kernel.number[p] for p in r["poi"]]
        assert len(out) == length and kernel.feasible(out, r["t"], hours=False)
        again = Kernel(k, cfg).run(method, f"t{i}", pois, t)
        assert (again["poi"], again["t"]) == (r["poi"], r["t"])


@pytest.mark.parametrize("form", ["reject", "chain"])
def test_fill_forms_stay_in_their_regions(form):
    k = city()
    kernel = Kernel(k, Cfg(fill=form))
    path = [8, 24 + 9, 48 + 11]
    p, t, smoothed, _ = kernel.fill("x", path)
    assert not smoothed and all(a in k.region_members[r] and s in k.region_slots[r] for a, s, r in zip(p, t, path))


def test_error_falls_with_the_budget():
    k = city()
    rows = [([k.poi_ids[i % 12], k.poi_ids[(i + 5) % 12], k.poi_ids[(i + 7) % 12]], [40, 60, 90]) for i in range(40)]
    def err(eps):
        kernel = Kernel(k, Cfg(eps=eps))
        return np.mean([np.abs(np.array(kernel.run("hier", f"t{i}", p, t)["t"]) - t).mean() for i, (p, t) in enumerate(rows)])
    assert err(500) < err(20) < err(0.01) + 5


def test_smoothing_moves_one_end():
    k = city()
    k.km = np.full_like(k.km, 7.3)  # 55 minutes at 8 km/h
    out = smooth(k, [0, 1, 2], [126, 127, 131], Cfg())
    assert all(b - a >= 6 for a, b in zip(out, out[1:])) and out[-1] <= 143
    assert smooth(k, list(range(12)) * 3, list(range(100, 136)), Cfg()) is None


def test_pick_ends():
    assert pick(np.array([0.0, 1.0, 0.0]), 0.999999) == 1 and pick(np.array([1.0, 1.0]), 0.6) == 1


def test_cheapest_predecessors_match_a_look_at_all():
    from pointveil.plans.kernel import SMALL, cheapest

    rng = np.random.default_rng(4)
    for n in (5, SMALL + 60):
        for share in (0.0, 0.01, 0.5):
            edge = rng.random((n, n)) < share
            edge[:, : n // 5] = False  # nodes that nothing leads to
            for nodes in (None, np.sort(rng.choice(n, n - 2, replace=False))):
                cost = rng.integers(0, 9, n if nodes is None else n - 2).astype(float)  # many ties
                cost[rng.random(len(cost)) < 0.2] = np.inf
                total = np.where(edge if nodes is None else edge[np.ix_(nodes, nodes)], cost[:, None], np.inf)
                best, least = cheapest(cost, edge, nodes)
                assert (least == total.min(axis=0)).all()
                assert (best == total.argmin(axis=0))[np.isfinite(least)].all()


def test_private_stage_is_dealt_to_all_cores(spark):
    from pyspark.sql import functions as F

    from pointveil import workloads
    from pointveil.plans import pipeline

    _, traj, k = workloads.event_city(spark, "/root/testdata/sf0.001", Cfg())
    rows = pipeline.run("indep_free", traj, k, Cfg(seed="7")).rows
    assert rows.select(F.spark_partition_id().alias("task")).distinct().count() > spark.sparkContext.defaultParallelism
