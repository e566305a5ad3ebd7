"""Hotspots: maximal runs of slots in which an entity has more unique visitors than a threshold, and their agreement."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .regions import grid_cell

#: Fixed values of the experiments: granularity -> threshold.
GRANULARITIES = {"poi": 20, "grid4": 20, "grid2": 50, "l1": 50, "l2": 30, "l3": 20}


def entity(granularity: str) -> Column:
    """The entity of a point at a granularity; points carry poi_id, lat, lon, l1, l2, l3."""
    if granularity.startswith("grid"):
        cy, cx = grid_cell(F.col("lat"), F.col("lon"), int(granularity[4:]))
        return F.concat_ws(":", cy.cast("string"), cx.cast("string"))
    return F.col("poi_id" if granularity == "poi" else granularity)


def visitors(traj: DataFrame, poi: DataFrame, granularity: str, slot_min: int = 60, gt_min: int = 10, approx: bool = False) -> DataFrame:
    """(entity, slot, n): unique trajectories per entity and slot; HLL instead of exact counting if asked."""
    p = traj.join(poi.select("poi_id", "lat", "lon", "l1", "l2", "l3"), "poi_id")
    n = F.approx_count_distinct("traj_id") if approx else F.countDistinct("traj_id")
    return p.groupBy(entity(granularity).alias("entity"), F.floor(F.col("t") * gt_min / slot_min).cast("int").alias("slot")).agg(n.alias("n"))


def find(counts: DataFrame, granularity: str, eta: float, strict: bool = True) -> DataFrame:
    """(granularity, entity, t_s, t_e, peak): runs above the threshold, end exclusive, in slots."""
    hot = counts.where(F.col("n") > eta if strict else F.col("n") >= eta)
    run = hot.withColumn("island", F.col("slot") - F.row_number().over(W.partitionBy("entity").orderBy("slot")))
    return run.groupBy("entity", "island").agg(F.min("slot").alias("t_s"), (F.max("slot") + 1).alias("t_e"), F.max("n").alias("peak")).select(F.lit(granularity).alias("granularity"), "entity", "t_s", "t_e", "peak")


def find_all(traj: DataFrame, poi: DataFrame, scale: float = 1.0, slot_min: int = 60, gt_min: int = 10) -> DataFrame:
    """Hotspots at every granularity in one pass, thresholds times ``scale``."""
    p = traj.join(F.broadcast(poi.select("poi_id", "lat", "lon", "l1", "l2", "l3")), "poi_id")
    kinds = F.array(*[F.struct(F.lit(g).alias("granularity"), F.lit(eta * scale).alias("eta"), entity(g).alias("entity")) for g, eta in GRANULARITIES.items()])
    each = p.select("traj_id", F.floor(F.col("t") * gt_min / slot_min).cast("int").alias("slot"), F.explode(kinds).alias("e")).select("traj_id", "slot", "e.*")
    n = each.groupBy("granularity", "eta", "entity", "slot").agg(F.countDistinct("traj_id").alias("n")).where("n > eta")
    return _runs(n, ())


def _runs(n: DataFrame, by: tuple[str, ...]) -> DataFrame:
    run = n.withColumn("island", F.col("slot") - F.row_number().over(W.partitionBy(*by, "granularity", "entity").orderBy("slot")))
    return run.groupBy(*by, "granularity", "entity", "island").agg(F.min("slot").alias("t_s"), (F.max("slot") + 1).alias("t_e"), F.max("n").alias("peak")).drop("island")


def of_counts(counts: DataFrame, scale: float = 1.0, by: tuple[str, ...] = ()) -> DataFrame:
    """``find_all`` from (by, granularity, entity, slot, n), for every value of ``by``."""
    eta = F.coalesce(*[F.when(F.col("granularity") == g, F.lit(eta * scale)) for g, eta in GRANULARITIES.items()])
    return _runs(counts.where(F.col("n") > eta), by)


COUNT_FIELDS = "granularity string, entity string, slot int, n long"


def counts_of_block(poi: DataFrame, poi_ids: list[str], slot_min: int = 60):
    """The unique visitors of every entity and slot in a block's released trajectories; a trajectory is in one block, so
    blocks add up. ``poi_ids``: the places of a checked catalog by number."""
    rows = {r.poi_id: r for r in poi.select("poi_id", *[entity(g).alias(f"{g}_") for g in GRANULARITIES]).collect()}
    kinds = [(g, *np.unique(np.array([rows[p][f"{g}_"] for p in poi_ids], dtype=object), return_inverse=True)) for g in GRANULARITIES]

    def tell(kernel, block, places: np.ndarray, slots: np.ndarray) -> dict[str, np.ndarray]:
        at, width, parts = block.t * kernel.cfg.gt_min // slot_min, 1440 // slot_min, []
        for granularity, names, code in kinds:
            cells = np.sort(code[block.poi] * width + at, axis=1)
            first = np.ones(cells.shape, dtype=bool)
            first[:, 1:] = cells[:, 1:] != cells[:, :-1]
            cell, n = np.unique(cells[first], return_counts=True)
            parts.append((np.full(len(cell), granularity, dtype=object), names[cell // width], (cell % width).astype(np.int32), n.astype(np.int64)))
        return dict(zip(("granularity", "entity", "slot", "n"), map(np.concatenate, zip(*parts))))

    return tell


def ahd_acd(real: DataFrame, out: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(granularity, ahd, acd, n_pairs, n_unmatched): each released hotspot against its nearest real one of the entity.

    ``by`` are columns of ``out`` alone, for the hotspots of many releases.
    """
    r = real.select("granularity", "entity", F.col("t_s").alias("r_s"), F.col("t_e").alias("r_e"), F.col("peak").alias("r_peak"))
    o = out.select(*by, "granularity", "entity", "t_s", "t_e", "peak")
    j = o.join(r, ["granularity", "entity"], "left")
    gap = F.abs(F.col("t_s") - F.col("r_s")) + F.abs(F.col("t_e") - F.col("r_e"))
    best = j.groupBy(*by, "granularity", "entity", "t_s", "t_e", "peak").agg(F.min(F.when(F.col("r_s").isNotNull(), F.struct(gap.alias("gap"), F.col("r_s"), F.col("r_peak")))).alias("m"))
    return best.groupBy(*by, "granularity").agg(
        F.round(F.avg("m.gap"), 6).alias("ahd"), F.round(F.avg(F.abs(F.col("peak") - F.col("m.r_peak"))), 6).alias("acd"),
        F.count("m").alias("n_pairs"), F.sum(F.col("m").isNull().cast("long")).alias("n_unmatched"),
    )


def compare(real: DataFrame, out: DataFrame) -> DataFrame:
    """All hotspots of both sides, missing ones included."""
    keys = ["granularity", "entity", "t_s", "t_e"]
    return real.withColumnRenamed("peak", "real_peak").join(out.withColumnRenamed("peak", "out_peak"), keys, "full_outer")
