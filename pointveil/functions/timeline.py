"""Slots of the day, coarse intervals and opening hours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def slot(ts: Column, gt_min: int = 10) -> Column:
    """Slot number of a timestamp within its day."""
    return F.floor((F.hour(ts) * 60 + F.minute(ts)) / gt_min).cast("int")


def day_slot(ts: Column) -> Column:
    """Slot number where one slot is a day of the month."""
    return F.dayofmonth(ts).cast("int")


def domain(spark: SparkSession, gt_min: int = 10) -> DataFrame:
    """All slots of a day with their first minute."""
    return spark.range(1440 // gt_min).select(F.col("id").cast("int").alias("slot"), (F.col("id") * gt_min).cast("int").alias("minute"))


def seen(points: DataFrame, gt_min: int = 10) -> DataFrame:
    """The slots in which points (column ts) fall, with their first minute."""
    slots = points.select(slot(F.col("ts"), gt_min).alias("slot")).distinct()
    return slots.select("slot", (F.col("slot") * gt_min).cast("int").alias("minute"))


def time_bin(hour: Column, width_h: int) -> Column:
    """First hour of the coarse interval that holds ``hour``."""
    return (F.floor(hour / width_h) * width_h).cast("int")


def is_open(hour: Column, open_h: Column, close_h: Column) -> Column:
    """Whether a venue is open in an hour; a closing time over 24 or before opening runs past midnight; null is always."""
    close = F.when(close_h < open_h, close_h + 24).otherwise(close_h)
    inside = ((hour >= open_h) & (hour < close)) | ((hour + 24 >= open_h) & (hour + 24 < close))
    return F.coalesce(inside, F.lit(True))


def joined_interval(a_start: Column, a_end: Column, b_start: Column, b_end: Column) -> tuple[Column, Column]:
    """Start and end of two touching intervals of the day, where one may follow the other over midnight."""
    wraps = (a_end % 24 == b_start % 24) & (a_start > b_start)
    start = F.when(wraps, a_start).otherwise(F.least(a_start, b_start))
    end = F.when(wraps, b_end + 24).otherwise(F.greatest(a_end, b_end))
    return start, end


def midpoint(start: Column, end: Column) -> Column:
    """Centre of an interval in hours, modulo a day."""
    return ((start + end) / 2.0) % 24.0
