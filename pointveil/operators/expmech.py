"""The exponential mechanism over candidate tables: its law, and the ways to draw from it.

A candidate table has key columns (one draw each), ``cand`` and ``dist``. The probability of a candidate is
proportional to exp(-eps dist / (2 delta)); delta is a public bound that no input changes.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.rng import gumbel, uniform


def sensitivity(n: int, diameter: float, mode: str = "diameter") -> float:
    """Public range of a window's distance: positions add up. 'unit' is for comparison only."""
    return 1.0 if mode == "unit" else n * diameter


def _score(eps: Column | float, delta: Column | float) -> Column:
    eps, delta = (x if isinstance(x, Column) else F.lit(float(x)) for x in (eps, delta))
    return -eps * F.col("dist") / (2 * delta)


def law(pairs: DataFrame, by: list[str], eps, delta) -> DataFrame:
    """The candidates with their probability p; shifted by the largest score, so large budgets don't underflow."""
    w = W.partitionBy(*by)
    scored = pairs.withColumn("s_", _score(eps, delta))
    raised = scored.withColumn("w_", F.exp(F.col("s_") - F.max("s_").over(w)))
    return raised.withColumn("p", F.col("w_") / F.sum("w_").over(w)).drop("s_", "w_")


def _keys(seed: str, by: list[str], *more) -> list:
    return [seed, *[F.col(b).cast("string") for b in by], *more]


def draw_cdf(pairs: DataFrame, by: list[str], eps, delta, seed: str) -> DataFrame:
    """Inverse of the running sum: the first candidate (in id order) whose sum reaches u."""
    run = W.partitionBy(*by).orderBy("cand").rowsBetween(W.unboundedPreceding, 0)
    summed = law(pairs, by, eps, delta).withColumn("cum", F.sum("p").over(run)).withColumn("u", uniform(*_keys(seed, by)))
    ok = summed.withColumn("rank_", F.when(F.col("cum") >= F.col("u"), F.struct(F.lit(0).alias("late"), "cand")).otherwise(F.struct(F.lit(1).alias("late"), "cand")))
    first = ok.groupBy(*by).agg(F.min(F.when(F.col("rank_.late") == 0, F.col("cand"))).alias("hit"), F.max("cand").alias("last"))
    return first.select(*by, F.coalesce("hit", "last").alias("chosen"))


def draw_gumbel(pairs: DataFrame, by: list[str], eps, delta, seed: str, kind: str = "md5") -> DataFrame:
    """Largest score plus Gumbel noise: one mergeable aggregate, no normaliser; ties to the larger id."""
    noisy = _score(eps, delta) + gumbel(uniform(*_keys(seed, by, F.col("cand").cast("string")), kind=kind))
    return pairs.withColumn("noisy_", noisy).groupBy(*by).agg(F.max(F.struct("noisy_", "cand")).alias("m")).select(*by, F.col("m.cand").alias("chosen"))


def draw_subsample(pairs: DataFrame, by: list[str], eps, delta, seed: str, rate: float) -> DataFrame:
    """The draw over a sample of the outputs that is picked without looking at the input."""
    kept = pairs.where(uniform(seed, "sample", F.col("cand").cast("string")) < rate)
    return draw_gumbel(kept, by, eps, delta, seed)


def draw_flip(pairs: DataFrame, by: list[str], eps, delta, seed: str) -> DataFrame:
    """Permute and flip by its published equal: score plus exponential noise, largest wins."""
    noise = -F.log(uniform(*_keys(seed, by, F.col("cand").cast("string"), "flip")))
    return pairs.withColumn("noisy_", _score(eps, delta) + noise).groupBy(*by).agg(F.max(F.struct("noisy_", "cand")).alias("m")).select(*by, F.col("m.cand").alias("chosen"))


def draw_flip_literal(pairs: DataFrame, by: list[str], eps, delta, seed: str) -> DataFrame:
    """Permute and flip step by step: candidates in seeded order, each accepted with its weight over the best; also trials."""
    w = W.partitionBy(*by)
    scored = pairs.withColumn("s_", _score(eps, delta))
    key = _keys(seed, by, F.col("cand").cast("string"))
    tried = scored.withColumn("ok", uniform(*key, "coin") <= F.exp(F.col("s_") - F.max("s_").over(w))).withColumn("turn", F.row_number().over(w.orderBy(uniform(*key, "order"), "cand")))
    first = tried.groupBy(*by).agg(F.min(F.when(F.col("ok"), F.struct("turn", "cand"))).alias("m"))
    return first.select(*by, F.col("m.cand").alias("chosen"), F.col("m.turn").alias("trials"))


def tail_bound(eps: float, delta: float, n_out: float, zeta: float, n_best: float = 1.0) -> float:
    """The loss that is passed with probability at most exp(-zeta)."""
    return 2 * delta / eps * (math.log(n_out / n_best) + zeta)
