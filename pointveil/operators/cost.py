"""Sizes the method has to face."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def log10_search_space(n_poi: int, length: int, gt_min: int, share: float = 1.0) -> float:
    """log10 of |P|^L times C(|T|, L), each next place cut to a share of all."""
    slots = 1440 // gt_min
    ln_choose = math.lgamma(slots + 1) - math.lgamma(length + 1) - math.lgamma(slots - length + 1)
    return (ln_choose + length * math.log(n_poi) + (length - 1) * math.log(share)) / math.log(10)


def log10_space(n_poi: Column, length: Column, gt_min: int, share: float = 1.0) -> Column:
    """``log10_search_space`` of columns."""
    slots = 1440 // gt_min
    steps = F.transform(F.sequence(F.lit(1), length), lambda i: F.log10((F.lit(slots) - length + i) / i))
    choose = F.aggregate(steps, F.lit(0.0), lambda s, v: s + v)
    return choose + length * F.log10(n_poi) + (length - 1) * math.log10(share)


def search_space(n_poi: int, length: int, gt_min: int, share: float = 1.0) -> float:
    """The same as a number; infinite past the range of doubles."""
    power = log10_search_space(n_poi, length, gt_min, share)
    return 10**power if power < 300 else math.inf


def program_size(n_regions: Column, length: Column) -> tuple[Column, Column]:
    """Variables as printed, and constraints, of one trajectory's programme."""
    return (n_regions * (length - 1)).cast("long"), ((n_regions + 1) * (length - 1)).cast("long")


def true_variables(edges: int, length: int) -> int:
    """Variables by definition: one per bigram and layer."""
    return edges * (length - 1)


def gram_space(z: DataFrame) -> DataFrame:
    """How many released windows there are, by length."""
    return z.groupBy(F.size("gram").alias("n")).agg(F.count(F.lit(1)).alias("windows"))
