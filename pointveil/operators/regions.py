"""Space-time-category regions: assignment, merging of sparse ones along a ladder, description."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..config import Cfg
from ..functions.timeline import midpoint, time_bin
from ..sources.io import staged
from ..sources.scenarios import BOX
from .catalog import open_hours


def grid_cell(lat: Column, lon: Column, gs: int, box: tuple[float, float, float, float] = BOX) -> tuple[Column, Column]:
    """Row and column of a gs x gs grid over a box (south, west, height, width); the border belongs inside."""
    south, west, high, wide = box
    clamp = lambda c: F.greatest(F.lit(0), F.least(F.lit(gs - 1), F.floor(c).cast("int")))
    return clamp((lat - south) / high * gs), clamp((lon - west) / wide * gs)


def cluster_cells(poi: DataFrame, k: int, seed: int = 7, rounds: int = 10) -> DataFrame:
    """(poi_id, cx, cy): k-means cells by plain Lloyd rounds; centres are k rows, broadcast each round."""
    from ..functions.rng import uniform

    start = poi.orderBy(uniform(str(seed), "poi_id"), "poi_id").limit(k).select("lat", "lon").collect()
    centres = [(r.lat, r.lon) for r in start]
    for _ in range(rounds):
        best = F.array_min(F.array(*[F.struct((F.pow(F.col("lat") - a, 2) + F.pow((F.col("lon") - b) * 0.76, 2)).alias("d"), F.lit(i).alias("i")) for i, (a, b) in enumerate(centres)]))["i"]
        means = {r.i: (r.a, r.b) for r in poi.groupBy(best.alias("i")).agg(F.avg("lat").alias("a"), F.avg("lon").alias("b")).collect()}
        moved = [means.get(i, c) for i, c in enumerate(centres)]
        if moved == centres:
            break
        centres = moved
    best = F.array_min(F.array(*[F.struct((F.pow(F.col("lat") - a, 2) + F.pow((F.col("lon") - b) * 0.76, 2)).alias("d"), F.lit(i).alias("i")) for i, (a, b) in enumerate(centres)]))["i"]
    return poi.select("poi_id", best.alias("cx"), F.lit(0).alias("cy"))


def admin_cells(poi: DataFrame, mapping: DataFrame) -> DataFrame:
    """(poi_id, cx, cy) where the cell is a known unit: mapping (poi_id, unit)."""
    return poi.join(mapping, "poi_id").select("poi_id", F.col("unit").cast("int").alias("cx"), F.lit(0).alias("cy"))


def category_node(level: int) -> Column:
    return F.col(f"l{level}")


def assign(poi: DataFrame, cfg: Cfg, cells: DataFrame | None = None, places: bool = False) -> DataFrame:
    """(poi_id, hour, cx_i, cy_i per grid step, l1, l2, l3) for every open hour; other cells replace the finest grid.
    ``places`` adds lat and lon."""
    out = open_hours(poi)
    for gs in cfg.gs_ladder:
        cy, cx = grid_cell(F.col("lat"), F.col("lon"), gs)
        out = out.withColumn(f"cy_{gs}", cy).withColumn(f"cx_{gs}", cx)
    if cells is not None:
        gs = cfg.gs_ladder[0]
        out = out.drop(f"cx_{gs}", f"cy_{gs}").join(cells.select("poi_id", F.col("cx").alias(f"cx_{gs}"), F.col("cy").alias(f"cy_{gs}")), "poi_id")
    return out.select("poi_id", "hour", *[f"{c}_{gs}" for gs in cfg.gs_ladder for c in ("cx", "cy")], "l1", "l2", "l3", "popularity", *[c for c in ("lat", "lon") if places])


def ladder(cfg: Cfg) -> list[tuple[int, int, int]]:
    """(grid, hours, level) of each merging step, the dimensions coarsening in the given order."""
    state = {"space": 0, "time": 0, "category": 0}
    sizes = {"space": len(cfg.gs_ladder), "time": len(cfg.t_ladder_h), "category": 3}
    steps = [dict(state)]
    for dim in cfg.merge_order:
        while state[dim] + 1 < sizes[dim]:
            state[dim] += 1
            steps.append(dict(state))
    return [(cfg.gs_ladder[s["space"]], cfg.t_ladder_h[s["time"]], 3 - s["category"]) for s in steps]


def _key(step: tuple[int, int, int]) -> list[Column]:
    gs, width, level = step
    return [
        F.lit(gs).alias("gs"), F.col(f"cx_{gs}").alias("cx"), F.col(f"cy_{gs}").alias("cy"), F.lit(width).alias("width"),
        time_bin(F.col("hour"), width).alias("t_start"), F.lit(level).alias("lvl"), F.col(f"l{level}").alias("node"),
    ]


KEY = ["gs", "cx", "cy", "width", "t_start", "lvl", "node"]


def merge(assigned: DataFrame, cfg: Cfg, weight: Column | None = None, cut=staged) -> tuple[DataFrame, DataFrame]:
    """Regions and their members (key columns, poi_id, hour).

    Under-full regions climb the ladder; what is full stays. ``weight`` is an aggregate to hold against kappa
    (number of places by default; sum of popularity keeps popular places alone), over one row a place however many hours
    it is open. What is still under-full at the top stays, flagged. ``cut`` stages each step's rows, or the plan would double at every step.
    """
    enough = F.countDistinct("poi_id") if weight is None else weight
    frontier, done = assigned, []
    steps = ladder(cfg)
    for i, step in enumerate(steps):
        keyed = frontier.select("*", *_key(step))
        sizes = (keyed if weight is None else keyed.dropDuplicates([*KEY, "poi_id"])).groupBy(*KEY).agg(enough.alias("size_"))
        joined = cut(keyed.join(sizes, KEY))
        last = i == len(steps) - 1
        full = joined if last else joined.where(F.col("size_") >= cfg.kappa)
        done.append(full.select(*KEY, "poi_id", "hour", (F.col("size_") < cfg.kappa).alias("under_full")))
        if not last and cut is staged and joined.where(F.col("size_") < cfg.kappa).isEmpty():
            break
        if not last:
            frontier = joined.where(F.col("size_") < cfg.kappa).select(*assigned.columns)
    members = done[0]
    for d in done[1:]:
        members = members.unionByName(d)
    regions = members.groupBy(*KEY).agg(F.countDistinct("poi_id").alias("n_poi"), F.max("under_full").alias("under_full"))
    return regions.withColumn("t_end", F.col("t_start") + F.col("width")), members


def merge_rows(assigned: pd.DataFrame, cfg: Cfg, weight: str | None = None) -> tuple[pd.DataFrame, pd.DataFrame]:
    """``merge`` and ``describe`` of a catalog whose size was checked, without a job for every step: (regions in order of
    their ids, members); ``assigned`` also has lat and lon, ``weight`` is a column to sum over places instead of counting them."""
    frontier, done, steps = assigned, [], ladder(cfg)
    for i, (gs, width, level) in enumerate(steps):
        hour = frontier["hour"]
        keyed = frontier.assign(gs=gs, cx=frontier[f"cx_{gs}"], cy=frontier[f"cy_{gs}"], width=width, t_start=hour - hour % width, lvl=level, node=frontier[f"l{level}"])
        # a place counts once, however many of its hours are in the region
        once = ~keyed.duplicated([*KEY, "poi_id"])
        size = keyed.assign(held=once if weight is None else keyed[weight].where(once, 0)).groupby(KEY)["held"].transform("sum")
        under = size < cfg.kappa
        full = keyed.assign(under_full=under) if i == len(steps) - 1 else keyed[~under].assign(under_full=False)
        done.append(full[[*KEY, "poi_id", "hour", "under_full", "lat", "lon"]])
        frontier = frontier[under]
        if not len(frontier):
            break
    members = pd.concat(done, ignore_index=True)
    members["region_id"] = members.groupby(KEY).ngroup()  # numbered in key order
    one = members.drop_duplicates(["region_id", "poi_id"]).sort_values(["region_id", "poi_id"])
    groups = one.groupby("region_id")
    out = groups[KEY].first().reset_index()
    out["n_poi"], out["under_full"] = groups.size().to_numpy(), members.groupby("region_id")["under_full"].max().to_numpy()
    out["t_end"] = out["t_start"] + out["width"]
    out["clat"], out["clon"] = np.round(groups["lat"].mean().to_numpy(), 9), np.round(groups["lon"].mean().to_numpy(), 9)
    out["set_id"], out["tmid"] = groups["poi_id"].agg(",".join).to_numpy(), (out["t_start"] + out["t_end"]) / 2.0 % 24.0
    return out, members[["region_id", "poi_id", "hour"]]


def describe(regions: DataFrame, members: DataFrame, poi: DataFrame) -> DataFrame:
    """Regions with id, centroid, time midpoint and the id of their place set; ids follow the key order."""
    p = members.select(*KEY, "poi_id").distinct().join(poi.select("poi_id", "lat", "lon"), "poi_id")
    stats = p.groupBy(*KEY).agg(F.round(F.avg("lat"), 9).alias("clat"), F.round(F.avg("lon"), 9).alias("clon"), F.md5(F.array_join(F.array_sort(F.collect_list("poi_id")), ",").cast("binary")).alias("set_id"))
    out = regions.join(stats, KEY)
    # regions are a public summary of one city (bounded by cells x nodes x bins), so one ordered window may number them
    number = F.row_number().over(W.orderBy(*KEY)) - 1
    return out.withColumn("tmid", midpoint(F.col("t_start"), F.col("t_end"))).withColumn("region_id", number.cast("long"))
