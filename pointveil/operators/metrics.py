"""Accuracy of a released set against the real one."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Cfg
from ..functions.distance import TIME_CAP_H, category, haversine_km, time_h
from .reach import valid_only


def point_errors(real: DataFrame, out: DataFrame, poi: DataFrame, gt_min: int = 10) -> DataFrame:
    """(traj_id, pos, d_t, d_c, d_s, d_all) per point; both sides join on (traj_id, pos), the key they are bucketed by."""
    p = poi.select("poi_id", "lat", "lon", "l3")
    a = real.select("traj_id", "pos", "poi_id", F.col("t").alias("t_a")).join(p, "poi_id").select("traj_id", "pos", "t_a", F.col("lat").alias("lat_a"), F.col("lon").alias("lon_a"), F.col("l3").alias("l3_a"))
    b = out.select("traj_id", "pos", "poi_id", F.col("t").alias("t_b")).join(p, "poi_id").select("traj_id", "pos", "t_b", F.col("lat").alias("lat_b"), F.col("lon").alias("lon_b"), F.col("l3").alias("l3_b"))
    j = a.join(b, ["traj_id", "pos"])
    d = j.select(
        "traj_id", "pos", time_h(F.col("t_a") * gt_min / 60.0, F.col("t_b") * gt_min / 60.0).alias("d_t"), category(F.col("l3_a"), F.col("l3_b")).alias("d_c"),
        F.round(haversine_km(F.col("lat_a"), F.col("lon_a"), F.col("lat_b"), F.col("lon_b")), 9).alias("d_s"),
    )
    return d.withColumn("d_all", F.sqrt(F.col("d_t") ** 2 + F.col("d_c") ** 2 + F.col("d_s") ** 2))


def ne(errors: DataFrame) -> DataFrame:
    """(dim, ne): mean over trajectories of the mean error of their points."""
    per = errors.groupBy("traj_id").agg(*[F.avg(d).alias(d) for d in ("d_t", "d_c", "d_s", "d_all")])
    long = per.select(F.explode(F.array(*[F.struct(F.lit(d[2:]).alias("dim"), F.col(d).alias("v")) for d in ("d_t", "d_c", "d_s", "d_all")])).alias("e"))
    return long.groupBy(F.col("e.dim").alias("dim")).agg(F.round(F.avg("e.v"), 6).alias("ne"))


def prq(errors: DataFrame, dim: str, deltas: list[float]) -> DataFrame:
    """(delta, pr): percentage of points within delta, averaged inside and then over trajectories."""
    each = errors.select("traj_id", F.col(dim).alias("d"), F.explode(F.array(*[F.lit(float(x)) for x in deltas])).alias("delta"))
    per = each.groupBy("traj_id", "delta").agg(F.avg((F.round("d", 6) <= F.col("delta")).cast("double")).alias("share"))
    return per.groupBy("delta").agg(F.round(100 * F.avg("share"), 6).alias("pr"))


def smoothing_rate(released: DataFrame) -> DataFrame:
    """Share of trajectories whose times had to be smoothed."""
    return released.groupBy("traj_id").agg(F.max("smoothed").alias("s")).agg(F.round(F.avg(F.col("s").cast("double")), 6).alias("rate"))


def feasible_rate(released: DataFrame, poi: DataFrame, cfg: Cfg, hours: bool = True) -> DataFrame:
    """Share of released trajectories that are reachable (and open) throughout."""
    good = valid_only(released.select("traj_id", "pos", "poi_id", "t"), poi, cfg, hours).select("traj_id").distinct().withColumn("ok", F.lit(1.0))
    return released.select("traj_id").distinct().join(good, "traj_id", "left").agg(F.round(F.avg(F.coalesce("ok", F.lit(0.0))), 6).alias("rate"))


def gain(table: DataFrame, ours: str = "hier") -> DataFrame:
    """(dim, gain): how far the method is below its best rival, as a share of the rival; table (method, dim, ne)."""
    rival = table.where(F.col("method") != ours).groupBy("dim").agg(F.min("ne").alias("rival"))
    mine = table.where(F.col("method") == ours).select("dim", F.col("ne").alias("mine"))
    return rival.join(mine, "dim").select("dim", F.round(1 - F.col("mine") / F.col("rival"), 6).alias("gain"))


def block_errors(kernel, block, places: np.ndarray, slots: np.ndarray) -> dict[str, np.ndarray]:
    """``point_errors`` of a block's released trajectories against the true ones, by trajectory and position."""
    t = np.minimum(np.abs(slots - block.t) * kernel.cfg.gt_min / 60.0, TIME_CAP_H)
    c, s = kernel.k.cat[places, block.poi], kernel.km9[places, block.poi]
    return {"d_t": t, "d_c": c, "d_s": s, "d_all": np.sqrt(t**2 + c**2 + s**2)}


#: Sums over the trajectories of one block, which add up to ``ne`` and to mean kernel seconds.
NE_FIELDS = "len int, n long, d_t double, d_c double, d_s double, d_all double, seconds double"


def ne_of_block(kernel, block, places: np.ndarray, slots: np.ndarray) -> dict[str, list]:
    n, length = places.shape
    sums = {dim: [float(e.mean(axis=1).sum())] for dim, e in block_errors(kernel, block, places, slots).items()}
    return {"len": np.array([length], dtype=np.int32), "n": [n], **sums, "seconds": [n * float(sum(block.stages))]}


PRQ_FIELDS = "dim string, delta double, n long, share double"


def prq_of_block(deltas: dict[str, list[float]]):
    """The summed shares of points within each delta of each dimension, which add up to ``prq``."""

    def tell(kernel, block, places: np.ndarray, slots: np.ndarray) -> dict[str, list]:
        errors = block_errors(kernel, block, places, slots)
        rows = [(dim, float(x), len(places), float((errors[dim].round(6) <= x).mean(axis=1).sum())) for dim, xs in deltas.items() for x in xs]
        return dict(zip(("dim", "delta", "n", "share"), map(list, zip(*rows))))

    return tell
