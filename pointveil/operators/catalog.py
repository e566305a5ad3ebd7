"""The public catalog of places."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.timeline import is_open
from ..schemas import POI, conform


def build(places: DataFrame) -> DataFrame:
    """Conform a catalog; rows without coordinates are rejected."""
    return conform(places, POI, not_null=("poi_id", "lat", "lon"))


def top_popular(poi: DataFrame, n: int) -> DataFrame:
    """The n most popular places; ties by id. A top-k, so no task sees all rows."""
    return poi.orderBy(F.desc("popularity"), "poi_id").limit(n)


def with_rank(poi: DataFrame) -> DataFrame:
    """Popularity rank inside each top category."""
    return poi.withColumn("rank", F.row_number().over(W.partitionBy("l1").orderBy(F.desc("popularity"), "poi_id")))


def with_hours(poi: DataFrame, rules: DataFrame, override: DataFrame | None = None) -> DataFrame:
    """Opening hours by category rule (l1, open_h, close_h), then by place (poi_id, open_h, close_h); none: always open."""
    out = poi.drop("open_h", "close_h").join(F.broadcast(rules.select("l1", "open_h", "close_h")), "l1", "left")
    if override is not None:
        o = override.select("poi_id", F.col("open_h").alias("o_open"), F.col("close_h").alias("o_close"))
        out = out.join(o, "poi_id", "left").withColumn("open_h", F.coalesce("o_open", "open_h")).withColumn("close_h", F.coalesce("o_close", "close_h")).drop("o_open", "o_close")
    return out


def open_hours(poi: DataFrame) -> DataFrame:
    """(poi_id, hour) for every hour in which a place is open."""
    each = poi.select("*", F.explode(F.sequence(F.lit(0), F.lit(23))).alias("hour"))
    return each.where(is_open(F.col("hour"), F.col("open_h"), F.col("close_h")))


def apply_delta(poi: DataFrame, delta: DataFrame, removed: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """The catalog after changed or new rows (and removed ids), and the touched ids."""
    touched = delta.select("poi_id") if removed is None else delta.select("poi_id").union(removed.select("poi_id"))
    kept = poi.join(touched, "poi_id", "left_anti")
    return kept.unionByName(delta), touched.distinct()


def weighted(poi: DataFrame, signal: DataFrame, share: float = 1.0) -> DataFrame:
    """Popularity raised by a (poi_id, mentions) signal such as comments."""
    return poi.join(signal, "poi_id", "left").withColumn("popularity", (F.col("popularity") + share * F.coalesce("mentions", F.lit(0))).cast("long")).drop("mentions")
