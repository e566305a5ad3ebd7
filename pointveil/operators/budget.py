"""How a trajectory's budget is split over its draws, and what has been spent."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import Cfg


def draws(length: Column, n: int, method: str) -> Column:
    """Number of draws by method: windows and end windows, plus one per time where times are drawn apart."""
    m = F.least(length, F.lit(n))
    if method == "hier":
        return length + m - 1
    if method in ("flat", "geo_only"):
        return 2 * length + m - 1
    if method in ("indep_free", "indep_reach"):
        return 2 * length
    return F.lit(1)


def split(length: Column, cfg: Cfg, method: str, total: Column | None = None) -> Column:
    """Budget of one draw: an equal share, or a constant; ``total`` may be a personal budget column."""
    if cfg.eps_mode == "per_draw":
        return F.lit(cfg.eps_draw)
    return (F.lit(cfg.eps) if total is None else total) / draws(length, cfg.n, method)


def split_value(length: int, cfg: Cfg, method: str, total: float | None = None) -> float:
    """The same in Python."""
    if cfg.eps_mode == "per_draw":
        return cfg.eps_draw
    m = min(length, cfg.n)
    count = {"hier": length + m - 1, "flat": 2 * length + m - 1, "geo_only": 2 * length + m - 1}.get(method, 2 * length if method.startswith("indep") else 1)
    return (cfg.eps if total is None else total) / count


def ledger(spent: DataFrame, by: list[str]) -> DataFrame:
    """Budgets add up: draws and total eps by key (a trajectory, or a person over all releases)."""
    return spent.groupBy(*by).agg(F.count(F.lit(1)).alias("draws"), F.round(F.sum("eps"), 9).alias("total"))
