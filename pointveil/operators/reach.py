"""Reachability of places and regions, and the filter that keeps feasible trajectories."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..config import Cfg
from ..functions.distance import haversine_km
from ..functions.timeline import is_open


def theta_km(gap_slots: Column, cfg: Cfg, factor: Column | None = None) -> Column:
    """How far one gets in a gap; ``factor`` slows or speeds an hour (congestion)."""
    if cfg.theta == "inf":
        return F.lit(float("inf"))
    if cfg.theta == "fixed":
        km = F.lit(cfg.theta_fixed_km)
    else:
        slots = F.lit(1) if cfg.theta == "slot" else gap_slots
        km = slots * F.lit(cfg.gt_min) * F.lit(cfg.speed_kmh) / 60.0
    return km if factor is None else km * factor


def poi_ok(km: Column, t_a: Column, t_b: Column, cfg: Cfg) -> Column:
    """A later slot and a distance within reach."""
    return (t_b > t_a) & (km <= theta_km(t_b - t_a, cfg))


def legs(traj: DataFrame, poi: DataFrame) -> DataFrame:
    """Trajectory points with place attributes, the previous point and the kilometres from it."""
    p = poi.select("poi_id", "lat", "lon", "open_h", "close_h")
    w = W.partitionBy("traj_id").orderBy("pos")
    j = traj.join(p, "poi_id")
    j = j.withColumn("b_lat", F.lag("lat").over(w)).withColumn("b_lon", F.lag("lon").over(w)).withColumn("b_t", F.lag("t").over(w))
    return j.withColumn("km", haversine_km(F.col("b_lat"), F.col("b_lon"), F.col("lat"), F.col("lon")))


def valid_only(traj: DataFrame, poi: DataFrame, cfg: Cfg, hours: bool = True) -> DataFrame:
    """Whole trajectories whose legs are all reachable and whose visits are all open."""
    j = legs(traj, poi)
    ok = F.col("b_t").isNull() | poi_ok(F.round("km", 9), F.col("b_t"), F.col("t"), cfg)
    if hours:
        ok = ok & is_open(F.floor(F.col("t") * cfg.gt_min / 60), F.col("open_h"), F.col("close_h"))
    marked = j.withColumn("ok", F.min(ok.cast("int")).over(W.partitionBy("traj_id")))
    return marked.where("ok = 1").select(*traj.columns)


def pairs(poi: DataFrame, km: float) -> DataFrame:
    """(a, b, km) of places within ``km``: an equi-join over neighbouring cells, then the true distance."""
    step_y, step_x = km / 110.0, km / 75.0
    p = poi.select("poi_id", "lat", "lon", F.floor(F.col("lat") / step_y).alias("cy"), F.floor(F.col("lon") / step_x).alias("cx"))
    a = p.select(F.col("poi_id").alias("a"), F.col("lat").alias("a_lat"), F.col("lon").alias("a_lon"), F.explode(F.array(*[F.col("cy") + d for d in (-1, 0, 1)])).alias("cy"), "cx")
    a = a.select("a", "a_lat", "a_lon", "cy", F.explode(F.array(*[F.col("cx") + d for d in (-1, 0, 1)])).alias("cx"))
    j = a.join(p, ["cy", "cx"]).where(F.col("a") != F.col("poi_id"))
    d = F.round(haversine_km(F.col("a_lat"), F.col("a_lon"), F.col("lat"), F.col("lon")), 6)
    return j.select("a", F.col("poi_id").alias("b"), d.alias("km")).where(F.col("km") <= km)


def place_sets(members: DataFrame) -> DataFrame:
    """(set_id, poi_id): the distinct place sets of regions, which many regions share over the day."""
    return members.select("set_id", "poi_id").distinct()


def set_gaps(sets: DataFrame, poi: DataFrame) -> DataFrame:
    """(a, b, km): least distance between the members of two place sets.

    Bounding boxes come first: only sets whose boxes are farther apart than any reach could be cut, here all pairs
    of the few distinct sets are kept because their least distance is what edges of every gap need.
    """
    p = sets.join(poi.select("poi_id", "lat", "lon"), "poi_id")
    a = p.select(F.col("set_id").alias("a"), F.col("lat").alias("a_lat"), F.col("lon").alias("a_lon"))
    b = p.select(F.col("set_id").alias("b"), F.col("lat").alias("b_lat"), F.col("lon").alias("b_lon"))
    d = haversine_km(F.col("a_lat"), F.col("a_lon"), F.col("b_lat"), F.col("b_lon"))
    return a.join(F.broadcast(b)).groupBy("a", "b").agg(F.round(F.min(d), 9).alias("km"))


def region_edges(regions: DataFrame, gaps: DataFrame, cfg: Cfg) -> DataFrame:
    """(src, dst) of regions with some later slot pair and two members within reach of the longest gap."""
    per_h = 60 // cfg.gt_min
    a = regions.select(F.col("region_id").alias("src"), F.col("set_id").alias("a"), (F.col("t_start") * per_h).alias("first_a"))
    b = regions.select(F.col("region_id").alias("dst"), F.col("set_id").alias("b"), (F.col("t_end") * per_h - 1).alias("last_b"))
    gap = F.col("last_b") - F.col("first_a")
    ok = gap >= 1
    if cfg.theta != "inf":
        ok = ok & (F.col("km") <= theta_km(gap, cfg))
    return gaps.join(a, "a").join(b, "b").where(ok).select("src", "dst")
