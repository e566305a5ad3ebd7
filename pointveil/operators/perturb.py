"""Encoding by regions and the overlapping windows of a trajectory: row-local, nothing of two people meets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def encode(traj: DataFrame, members: DataFrame, gt_min: int = 10) -> DataFrame:
    """Points with the least region id that holds the place in its hour; none found gives a null, never a lost row."""
    m = members.groupBy("poi_id", "hour").agg(F.min("region_id").alias("region_id"))
    return traj.withColumn("hour", F.floor(F.col("t") * gt_min / 60).cast("int")).join(m, ["poi_id", "hour"], "left").drop("hour")


def packed(traj: DataFrame, *columns: str) -> DataFrame:
    """One row per trajectory: traj_id, len, seq array<struct<pos, columns>> in order."""
    g = traj.groupBy("traj_id").agg(F.array_sort(F.collect_list(F.struct("pos", *columns))).alias("seq"))
    return g.select("traj_id", F.size("seq").alias("len"), "seq")


def unpacked(rows: DataFrame) -> DataFrame:
    """The points of packed trajectories."""
    return rows.select("traj_id", F.inline("seq"))


def _slice(seq: Column, a: Column, b: Column) -> Column:
    return F.slice(seq, a, b - a + 1)


def windows(rows: DataFrame, seq: str, n: int, overlap: bool = True) -> DataFrame:
    """Main windows (traj_id, a, b, gram, kind); shorter trajectories are one window; disjoint ones step by n."""
    size = F.size(seq)
    m = F.least(size, F.lit(n))
    stop = F.when(F.lit(overlap), size - m + 1).otherwise(size)
    each = rows.select("traj_id", F.col(seq), F.explode(F.sequence(F.lit(1), stop, F.lit(1) if overlap else m)).alias("a"))
    b = F.least(F.col("a") + n - 1, F.size(seq))
    return each.select("traj_id", "a", b.cast("int").alias("b"), _slice(F.col(seq), F.col("a"), b).alias("gram"), F.lit("main").alias("kind"))


def end_windows(rows: DataFrame, seq: str, n: int) -> DataFrame:
    """Prefixes and suffixes of 1 to n-1 points, which give the ends as many windows as the middle."""
    size = F.size(seq)
    m = F.least(size, F.lit(n)) - 1
    each = rows.where(m >= 1).select("traj_id", F.col(seq), F.explode(F.sequence(F.lit(1), m)).alias("k"))
    first = each.select("traj_id", F.lit(1).alias("a"), F.col("k").alias("b"), _slice(F.col(seq), F.lit(1), F.col("k")).alias("gram"), F.lit("prefix").alias("kind"))
    last = each.select("traj_id", (size - F.col("k") + 1).alias("a"), size.alias("b"), _slice(F.col(seq), size - F.col("k") + 1, size).alias("gram"), F.lit("suffix").alias("kind"))
    return first.unionByName(last)


def all_windows(rows: DataFrame, seq: str, n: int) -> DataFrame:
    return windows(rows, seq, n).unionByName(end_windows(rows, seq, n))


def votes(z: DataFrame) -> DataFrame:
    """(traj_id, pos, region_id): every region that some released window puts at a position."""
    return z.select("traj_id", F.posexplode("gram").alias("i", "region_id"), "a").select("traj_id", (F.col("a") + F.col("i")).alias("pos"), "region_id")
