"""Checks of privacy and structure; each returns failing rows or a small report."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ratio_bound(law: DataFrame, eps: Column | float, by: str = "cand") -> DataFrame:
    """(worst, bound, ok): largest ratio of an output's probabilities over inputs against e^eps (or e^f)."""
    worst = law.groupBy(by).agg((F.max("p") / F.min("p")).alias("ratio"))
    e = eps if isinstance(eps, Column) else F.lit(float(eps))
    return worst.agg(F.max("ratio").alias("worst")).select("worst", F.exp(e).alias("bound"), (F.col("worst") <= F.exp(e) * (1 + 1e-9)).alias("ok"))


def empirical_eps(law: DataFrame, by: str = "cand") -> DataFrame:
    """(eps): the log of the worst ratio."""
    return law.groupBy(by).agg(F.log(F.max("p") / F.min("p")).alias("e")).agg(F.max("e").alias("eps"))


def coverage(windows: DataFrame, n: int) -> DataFrame:
    """Positions that are not in exactly min(n, length) windows."""
    size = windows.groupBy("traj_id").agg(F.max("b").alias("len"))
    seen = windows.select("traj_id", F.explode(F.sequence("a", "b")).alias("pos")).groupBy("traj_id", "pos").agg(F.count(F.lit(1)).alias("times"))
    return seen.join(size, "traj_id").where(F.col("times") != F.least(F.col("len"), F.lit(n)))


def tail_check(pairs: DataFrame, law: DataFrame, bound: float) -> DataFrame:
    """Probability that the loss passes a bound, per input: the law's mass there."""
    return law.groupBy("input").agg(F.sum(F.when(F.col("dist") - 0 > bound, F.col("p")).otherwise(0.0)).alias("mass"))


def continuity(paths: DataFrame, edges: DataFrame) -> DataFrame:
    """Consecutive regions of (traj_id, pos, region_id) that are no edge."""
    a = paths.select("traj_id", "pos", F.col("region_id").alias("src"))
    b = paths.select("traj_id", (F.col("pos") - 1).alias("pos"), F.col("region_id").alias("dst"))
    return a.join(b, ["traj_id", "pos"]).join(edges, ["src", "dst"], "left_anti")


def is_row_local(df: DataFrame) -> bool:
    """Whether the plan moves no rows between tasks."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return re.search(r"Exchange|Aggregate|SortMergeJoin|ShuffledHashJoin|Window\b", plan) is None


def assert_row_local(df: DataFrame) -> None:
    """The private zone must be row-local: no shuffle, aggregate or join of two people's rows."""
    if not is_row_local(df):
        raise AssertionError("rows of different people may meet in this plan")
