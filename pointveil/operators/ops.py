"""Surrounding operators: as-of joins, set deltas, roll-ups, patterns of released sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """``left`` with the last ``value`` of ``right`` at or before its time: one union and one running last, no range join."""
    kinds = [f.name for f in left.schema if f.name not in (key, time)]
    a = left.select(key, time, *kinds, F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("side_"))
    b = right.select(key, time, *[F.lit(None).cast(left.schema[k].dataType).alias(k) for k in kinds], value, F.lit(0).alias("side_"))
    w = W.partitionBy(key).orderBy(time, "side_").rowsBetween(W.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last(value, ignorenulls=True).over(w)).where("side_ = 1").drop("side_")


def last_before(events: DataFrame, key: str, order: list[str], value: str, out: str) -> DataFrame:
    """Every row with the value of the row before it."""
    return events.withColumn(out, F.lag(value).over(W.partitionBy(key).orderBy(*order)))


def trip_chains(released: DataFrame, k: int = 20) -> DataFrame:
    """The k commonest place-to-place steps; ties by names."""
    w = W.partitionBy("traj_id").orderBy("pos")
    steps = released.select(F.col("poi_id").alias("from"), F.lead("poi_id").over(w).alias("to")).where("to IS NOT NULL")
    return steps.groupBy("from", "to").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "from", "to").limit(k)


def next_category(released: DataFrame, poi: DataFrame) -> DataFrame:
    """(l1, next_l1, n, rate): which category follows which, as a share of all steps from it."""
    w = W.partitionBy("traj_id").orderBy("pos")
    s = released.join(poi.select("poi_id", "l1"), "poi_id").select("l1", F.lead("l1").over(w).alias("next_l1")).where("next_l1 IS NOT NULL")
    c = s.groupBy("l1", "next_l1").agg(F.count(F.lit(1)).alias("n"))
    return c.select("l1", "next_l1", "n", F.round(F.col("n") / F.sum("n").over(W.partitionBy("l1")), 6).alias("rate"))


def copresence(released: DataFrame) -> DataFrame:
    """(poi_id, slot, pairs): how many pairs of trajectories share a place and slot, by counting, not pairing."""
    c = released.groupBy("poi_id", F.col("t").alias("slot")).agg(F.countDistinct("traj_id").alias("n"))
    return c.where("n > 1").select("poi_id", "slot", (F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("pairs"))


def set_delta(old: DataFrame, new: DataFrame) -> DataFrame:
    """Rows only in one of two edge sets, with their side."""
    return old.exceptAll(new).withColumn("side", F.lit("old")).unionByName(new.exceptAll(old).withColumn("side", F.lit("new")))


def hash_sample(df: DataFrame, key: str, rate: float, seed: str) -> DataFrame:
    """A sample that the same key always falls into."""
    from ..functions.rng import uniform

    return df.where(uniform(seed, F.col(key).cast("string"), kind="xx") < rate)
