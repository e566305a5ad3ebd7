"""Experiments in one job: errors, ranges and hotspots told by blocks against the DataFrame measures of one release."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from pointveil import workloads
from pointveil.config import Cfg
from pointveil.operators import hotspots, metrics, regions
from pointveil.operators.perturb import unpacked
from pointveil.plans import knowledge, pipeline
from pointveil.sources import scenarios as S

D = "/root/testdata/sf0.001"
CFG = Cfg(seed="7", delta_mode="unit")


@pytest.fixture(scope="module")
def packs(spark):
    return workloads.event_packs(spark, D, CFG)


def _rows(df, *by):
    return df.toPandas().sort_values(list(by)).reset_index(drop=True)[sorted(df.columns)]


def test_packs_are_the_valid_trajectories(spark, packs):
    from pointveil.operators import reach

    want = reach.valid_only(S.event_traj(spark, D), packs[0], CFG)
    pd.testing.assert_frame_equal(_rows(unpacked(packs[1]), "traj_id", "pos"), _rows(want, "traj_id", "pos"))


@pytest.mark.parametrize("method", workloads.ALL_METHODS)
def test_told_errors_are_those_of_the_joined_release(packs, method):
    poi, rows, k = packs
    out = workloads.released(method, unpacked(rows), k, CFG).released
    errors = metrics.point_errors(unpacked(rows), out, poi)
    want = {r.dim: r.ne for r in metrics.ne(errors).collect()}
    both = workloads._ne(rows, [(method, k, CFG, {"x": 1}), ("indep_free", k, CFG.but(eps=50.0), {"x": 2})], True)
    got = both.where("x = 1").collect()
    assert {r.dim: r.ne for r in got} == pytest.approx(want, abs=2e-6) and {r.method for r in got} == {method}
    assert both.count() == 8 and min(r.seconds for r in got) > 0
    deltas = {"d_s": [0.05, 1, 4], "d_t": [0.5, 2], "d_c": [0, 2, 5]}
    told = workloads._sums(rows, [(method, k, CFG, {})], metrics.prq_of_block(deltas), metrics.PRQ_FIELDS, ("dim", "delta"))
    got = {(r.dim, r.delta): 100 * r.share / r.n for r in told.collect()}
    want = {(dim, r.delta): r.pr for dim, xs in deltas.items() for r in metrics.prq(errors, dim, xs).collect()}
    assert got == pytest.approx(want, abs=1e-5)
    counts = workloads._sums(rows, [(method, k, CFG, {})], hotspots.counts_of_block(poi, k.poi_ids), hotspots.COUNT_FIELDS, ("granularity", "entity", "slot"))
    found = hotspots.of_counts(counts, 0.05, ("method",)).drop("method")
    want, key = hotspots.find_all(out, poi, 0.05), ("granularity", "entity", "t_s")
    pd.testing.assert_frame_equal(_rows(found, *key), _rows(want, *key), check_dtype=False)
    assert found.count() > 10


def test_releases_are_one_job_without_a_join(packs):
    _, rows, k = packs
    told = pipeline.measured(rows, [(m, k, CFG) for m in workloads.ALL_METHODS], metrics.ne_of_block, metrics.NE_FIELDS)
    plan = told._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 5 and "Join" not in plan and "Window" not in plan
    assert told.agg(F.sum("n")).first()[0] == 5 * rows.count()


@pytest.mark.parametrize("changes,weight", [({}, None), ({"kappa": 5}, None), ({"merge_order": ("category", "space", "time")}, None), ({"kappa": 20}, "popularity")], ids=str)
def test_merged_rows_are_those_of_the_plan(spark, packs, changes, weight):
    poi, cfg = packs[0], Cfg(**changes)
    merged, members = regions.merge(regions.assign(poi, cfg), cfg, weight and F.sum(weight))
    want = regions.describe(merged, members, poi).toPandas().sort_values("region_id").reset_index(drop=True)
    k = knowledge.build(poi, cfg, weight=weight)
    same = [*regions.KEY, "region_id", "n_poi", "under_full", "t_end", "tmid", "clat", "clon"]
    pd.testing.assert_frame_equal(k.regions[same], want[same], check_dtype=False)
    pairs = lambda s: s.to_numpy()[:, None] == s.to_numpy()
    assert np.array_equal(pairs(k.regions["set_id"]), pairs(want["set_id"]))
    held = members.join(F.broadcast(spark.createDataFrame(want[[*regions.KEY, "region_id"]])), regions.KEY).select("region_id", "poi_id", "hour")
    assert sorted(map(tuple, held.collect())) == sorted(k.members.itertuples(index=False, name=None))


def test_popularity_threshold_goes_with_the_table(spark, tmp_path):
    """With a fixed number of visits a table of a hundred times as many merges nothing and is refused."""
    once = spark.read.parquet(f"{D}/events.parquet")
    more = once.crossJoin(spark.range(100).withColumnRenamed("id", "copy"))
    more.withColumns({"user_id": F.col("user_id") + 15 * F.col("copy"), "event_id": F.col("event_id") + 1000 * F.col("copy")}).drop("copy").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    regions_of = lambda d: {r.order: r.regions for r in workloads.QUERIES["wk_merge_ablation"](spark, d).collect()}
    assert regions_of(str(tmp_path)) == regions_of(D)


def test_length_sweep_builds_the_city_once(spark, monkeypatch):
    from pointveil import workloads
    from pointveil.plans import knowledge

    built, build = [], knowledge.build
    monkeypatch.setattr(knowledge, "build", lambda *a, **k: built.append(1) or build(*a, **k))
    rows = workloads.wk_vary_len(spark, "/root/testdata/sf0.001").collect()
    assert len(built) == 1 and {r.scenario for r in rows} == {"event_city", "panel_city"}


def test_merge_ablation_has_every_order_and_threshold(spark):
    """Six orders by three thresholds, of places and of popularity; three orders at one threshold were the most."""
    from itertools import permutations

    rows = workloads.QUERIES["wk_merge_ablation"](spark, D).collect()
    visits, places = S.event_poi(spark, D).agg(F.sum("popularity"), F.count(F.lit(1))).first()
    names = ["-".join(o) for o in permutations(("space", "time", "category"))]
    popular = ["popularity", *[f"popularity-{n}" for n in names[1:]]]
    kappas = {"plain": (3, 5, 10), "popular": [-(-n * visits // places) for n in (3, 5, 10)]}
    want = {(o, k) for o in names for k in kappas["plain"]} | {(o, k) for o in popular for k in kappas["popular"]}
    assert {(r.order, r.kappa) for r in rows} == want and len(rows) == 4 * 36
    assert {r.dim for r in rows} == {"t", "c", "s", "all"} and all(r.regions > 0 and r.ne >= 0 for r in rows)


@pytest.mark.parametrize("joined", [False, True], ids=["rows", "plan"])
def test_a_place_weighs_once_however_long_it_is_open(spark, joined):
    """Two places of 6 and 5 visits, open all day: held against 10 at 24 hours together, not at 2 hours each alone."""
    poi = spark.createDataFrame([("a", 40.71, -74.01, "x", "x/0", "x/0/0", 0, 24, 6), ("b", 40.71, -74.01, "x", "x/0", "x/0/1", 0, 24, 5)], "poi_id string, lat double, lon double, l1 string, l2 string, l3 string, open_h int, close_h int, popularity long")
    cfg = Cfg(kappa=10, merge_order=("time", "category", "space"))
    if joined:
        found = regions.merge(regions.assign(poi, cfg), cfg, F.sum("popularity"))[0].toPandas()
    else:
        found = regions.merge_rows(regions.assign(poi, cfg, None, True).toPandas(), cfg, "popularity")[0]
    assert found[["width", "lvl", "n_poi"]].values.tolist() == [[24, 2, 2]]
