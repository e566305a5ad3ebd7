"""Rebuilding a trajectory from released windows, as DataFrame plans (the fused form is in plans.kernel)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..config import Cfg
from ..functions.distance import haversine_km


def mbr(votes: DataFrame, region_boxes: DataFrame) -> DataFrame:
    """Bounding box of all places of the voted regions: traj_id, south, north, west, east."""
    j = votes.join(region_boxes, "region_id")
    return j.groupBy("traj_id").agg(F.min("south").alias("south"), F.max("north").alias("north"), F.min("west").alias("west"), F.max("east").alias("east"))


def boxes(members: DataFrame, poi: DataFrame) -> DataFrame:
    """Box of each region's places."""
    j = members.select("region_id", "poi_id").distinct().join(poi.select("poi_id", "lat", "lon"), "poi_id")
    return j.groupBy("region_id").agg(F.min("lat").alias("south"), F.max("lat").alias("north"), F.min("lon").alias("west"), F.max("lon").alias("east"))


def candidates(box: DataFrame, region_boxes: DataFrame) -> DataFrame:
    """(traj_id, region_id) of regions with a place box that meets the trajectory's box."""
    r = F.broadcast(region_boxes.select("region_id", F.col("south").alias("s"), F.col("north").alias("n"), F.col("west").alias("w"), F.col("east").alias("e")))
    meets = (F.col("s") <= F.col("north")) & (F.col("n") >= F.col("south")) & (F.col("w") <= F.col("east")) & (F.col("e") >= F.col("west"))
    return box.join(r, meets).select("traj_id", "region_id")


def node_error(votes: DataFrame, distances: DataFrame) -> DataFrame:
    """(traj_id, pos, region_id, err): distance from a region to all votes of a position; distances (src, dst, d)."""
    counted = votes.groupBy("traj_id", "pos", "region_id").agg(F.count(F.lit(1)).alias("k"))
    j = counted.join(distances, counted.region_id == distances.src)
    return j.groupBy("traj_id", "pos", F.col("dst").alias("region_id")).agg(F.round(F.sum(F.col("k") * F.col("d")), 6).alias("err"))


def edge_error(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(traj_id, pos, src, dst, err): left node at pos plus right node at pos + 1."""
    a = nodes.select("traj_id", "pos", F.col("region_id").alias("src"), F.col("err").alias("left_err"))
    b = nodes.select("traj_id", (F.col("pos") - 1).alias("pos"), F.col("region_id").alias("dst"), F.col("err").alias("right_err"))
    return a.join(edges, "src").join(b, ["traj_id", "pos", "dst"]).select("traj_id", "pos", "src", "dst", F.round(F.col("left_err") + F.col("right_err"), 6).alias("err"))


def best_path(edge_err: DataFrame, length: int) -> DataFrame:
    """(traj_id, cost, path): least total over continuous bigrams, one join and one min per position (no enumeration)."""
    state = edge_err.where("pos = 1").groupBy("traj_id", F.col("dst").alias("at")).agg(F.min(F.struct(F.col("err").alias("cost"), F.array("src", "dst").alias("path"))).alias("m"))
    for i in range(2, length):
        step = edge_err.where(F.col("pos") == i).select("traj_id", F.col("src").alias("at"), "dst", "err")
        j = state.join(step, ["traj_id", "at"])
        grown = F.struct(F.round(F.col("m.cost") + F.col("err"), 6).alias("cost"), F.concat("m.path", F.array("dst")).alias("path"))
        state = j.groupBy("traj_id", F.col("dst").alias("at")).agg(F.min(grown).alias("m"))
    return state.groupBy("traj_id").agg(F.min("m").alias("m")).select("traj_id", F.col("m.cost").alias("cost"), F.col("m.path").alias("path"))


def as_program(edge_err: DataFrame) -> DataFrame:
    """The 0/1 programme of the path: one row per coefficient (traj_id, family, row, var, coef, sense, rhs).

    Variables are (layer, src, dst). Families: objective, one bigram per layer, continuity between layers.
    """
    var = F.concat_ws(":", F.col("pos").cast("string"), F.col("src").cast("string"), F.col("dst").cast("string"))
    v = edge_err.withColumn("var", var)
    goal = v.select("traj_id", F.lit("objective").alias("family"), F.lit("min").alias("row"), "var", F.col("err").alias("coef"), F.lit("min").alias("sense"), F.lit(0.0).alias("rhs"))
    one = v.select("traj_id", F.lit("layer").alias("family"), F.col("pos").cast("string").alias("row"), "var", F.lit(1.0).alias("coef"), F.lit("=").alias("sense"), F.lit(1.0).alias("rhs"))
    last = W.partitionBy("traj_id")
    v = v.withColumn("top", F.max("pos").over(last))
    into = v.where("pos < top").select("traj_id", F.lit("continuity").alias("family"), F.concat_ws(":", (F.col("pos") + 1).cast("string"), F.col("dst").cast("string")).alias("row"), "var", F.lit(1.0).alias("coef"), F.lit("=").alias("sense"), F.lit(0.0).alias("rhs"))
    out = v.where("pos > 1").select("traj_id", F.lit("continuity").alias("family"), F.concat_ws(":", F.col("pos").cast("string"), F.col("src").cast("string")).alias("row"), "var", F.lit(-1.0).alias("coef"), F.lit("=").alias("sense"), F.lit(0.0).alias("rhs"))
    return goal.unionByName(one).unionByName(into).unionByName(out)


def need_slots(traj: DataFrame, poi: DataFrame, cfg: Cfg) -> DataFrame:
    """Points with the slots needed from the previous point: at least one, or the travel time rounded up."""
    w = W.partitionBy("traj_id").orderBy("pos")
    j = traj.join(poi.select("poi_id", "lat", "lon"), "poi_id")
    km = haversine_km(F.lag("lat").over(w), F.lag("lon").over(w), F.col("lat"), F.col("lon"))
    return j.withColumn("need", F.when(km.isNull(), 0).otherwise(F.greatest(F.lit(1), F.ceil(F.round(km, 6) / cfg.speed_kmh * 60 / cfg.gt_min))).cast("int")).drop("lat", "lon")


def smooth_times(needs: DataFrame, slots: int = 144) -> DataFrame:
    """Later times move forward as little as needed; if the day ends first, the overrun is taken back from the end.

    Forward: t'_i is the largest of t_j + need(j+1..i), a running maximum of t - cumulative need. Backward, from
    the day's last slot: the least of what is left for the legs to come.
    """
    w = W.partitionBy("traj_id").orderBy("pos").rowsBetween(W.unboundedPreceding, 0)
    after = W.partitionBy("traj_id").orderBy("pos").rowsBetween(0, W.unboundedFollowing)
    c = needs.withColumn("cum", F.sum("need").over(w))
    f = c.withColumn("t1", F.max(F.col("t") - F.col("cum")).over(w) + F.col("cum"))
    g = f.withColumn("t2", F.least(F.col("t1"), F.lit(slots - 1)))
    g = g.withColumn("t3", F.min(F.col("t2") - F.col("cum")).over(after) + F.col("cum"))
    return g.select("traj_id", "pos", "poi_id", F.col("t3").cast("int").alias("t"))
