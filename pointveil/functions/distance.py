"""Distances of places, times, categories and regions, and the registry of other ones."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EARTH_KM, TIME_CAP_H, FAR_CATEGORY = 6371.0, 12.0, 10.0


def haversine_km(lat_a: Column, lon_a: Column, lat_b: Column, lon_b: Column) -> Column:
    """Great-circle distance."""
    h = F.pow(F.sin(F.radians(lat_b - lat_a) / 2), 2) + F.cos(F.radians(lat_a)) * F.cos(F.radians(lat_b)) * F.pow(F.sin(F.radians(lon_b - lon_a) / 2), 2)
    return 2 * EARTH_KM * F.asin(F.sqrt(F.least(F.lit(1.0), h)))


def euclid_km(lat_a: Column, lon_a: Column, lat_b: Column, lon_b: Column) -> Column:
    """Flat distance: degrees scaled by the mean latitude."""
    k = F.lit(EARTH_KM) * F.radians(F.lit(1.0))
    return F.sqrt(F.pow((lat_b - lat_a) * k, 2) + F.pow((lon_b - lon_a) * k * F.cos(F.radians((lat_a + lat_b) / 2)), 2))


def by_table(pairs: DataFrame, od: DataFrame, default: Column) -> DataFrame:
    """``pairs`` (src, dst, hour) with km from an origin-destination table, which may be asymmetric and vary by hour."""
    return pairs.join(od.select("src", "dst", "hour", F.col("km").alias("od_km")), ["src", "dst", "hour"], "left").withColumn("km", F.coalesce("od_km", default)).drop("od_km")


def time_h(a: Column, b: Column, mode: str = "cap") -> Column:
    """Hours between two times of the day, at most 12; 'circular' goes over midnight where that is shorter."""
    gap = F.abs(a - b)
    return F.least(gap, 24.0 - gap) if mode == "circular" else F.least(gap, F.lit(TIME_CAP_H))


#: Category distances by the levels of two nodes and of their last common ancestor (0 where the roots differ).
CATEGORY_TABLE = {(3, 3, 2): 2.0, (3, 3, 1): 5.0, (2, 3, 2): 1.0, (1, 3, 1): 3.0, (1, 2, 1): 2.0, (2, 2, 1): 4.0, (2, 3, 1): 4.5}


def category(path_a: Column, path_b: Column, table: dict = CATEGORY_TABLE) -> Column:
    """Distance of two tree nodes given as 'a/b/c' paths; a level table, symmetric, 10 across roots."""
    a, b = F.split(path_a, "/"), F.split(path_b, "/")
    low, high = F.least(F.size(a), F.size(b)), F.greatest(F.size(a), F.size(b))
    common = F.aggregate(F.zip_with(a, b, lambda x, y: x.eqNullSafe(y)), F.struct(F.lit(0).alias("n"), F.lit(True).alias("on")),
                         lambda s, e: F.struct((s["n"] + (s["on"] & e).cast("int")).alias("n"), (s["on"] & e).alias("on")), lambda s: s["n"])
    out = F.when(path_a == path_b, 0.0)
    for (x, y, c), v in table.items():
        out = out.when((low == x) & (high == y) & (common == c), v)
    return out.otherwise(FAR_CATEGORY)


def category_value(a: str, b: str, table: dict = CATEGORY_TABLE) -> float:
    """The same in Python, for kernels' tables."""
    if a == b:
        return 0.0
    x, y = a.split("/"), b.split("/")
    common = 0
    while common < min(len(x), len(y)) and x[common] == y[common]:
        common += 1
    return table.get((*sorted((len(x), len(y))), common), FAR_CATEGORY)


def category_sql(a: str, b: str) -> str:
    """The same in DuckDB, for three-level paths."""
    part = "split_part({0},'/',{1})"
    n = "len(string_split({0},'/'))"
    same = [" AND ".join(f"{part.format(a, i)} = {part.format(b, i)}" for i in range(1, k + 1)) for k in (1, 2, 3)]
    common = f"(CASE WHEN {same[0]} THEN CASE WHEN {same[1]} AND least({n.format(a)},{n.format(b)}) >= 2 THEN 2 ELSE 1 END ELSE 0 END)"
    cases = " ".join(f"WHEN least({n.format(a)},{n.format(b)}) = {x} AND greatest({n.format(a)},{n.format(b)}) = {y} AND {common} = {c} THEN {v}" for (x, y, c), v in CATEGORY_TABLE.items())
    return f"(CASE WHEN {a} = {b} THEN 0.0 {cases} ELSE {FAR_CATEGORY} END)::DOUBLE"


def haversine_sql(la: str, lo: str, lb: str, lp: str) -> str:
    """Great-circle distance in DuckDB."""
    h = f"pow(sin(radians({lb} - {la}) / 2), 2) + cos(radians({la})) * cos(radians({lb})) * pow(sin(radians({lp} - {lo}) / 2), 2)"
    return f"(2 * {EARTH_KM} * asin(sqrt(least(1.0, {h}))))"


def combined(d_s: Column, d_t: Column, d_c: Column) -> Column:
    """Norm of the three."""
    return F.sqrt(d_s * d_s + d_t * d_t + d_c * d_c)


def gram(xs: Column, ys: Column, each: Callable[[Column, Column], Column]) -> Column:
    """Sum over positions of two equally long arrays."""
    return F.aggregate(F.zip_with(xs, ys, each), F.lit(0.0), lambda s, d: s + d)


def vector_l2(a: Column, b: Column) -> Column:
    """Euclidean distance of two embedding arrays, in doubles."""
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: F.pow(x.cast("double") - y.cast("double"), 2)), F.lit(0.0), lambda s, d: s + d))


def vector_cosine(a: Column, b: Column) -> Column:
    """One minus the cosine of two embedding arrays."""
    dot = lambda p, q: F.aggregate(F.zip_with(p, q, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, d: s + d)
    return 1 - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


_REGISTRY: dict[str, tuple[Callable, float]] = {}


def register(name: str, fn: Callable, diameter: float) -> None:
    """Make another quality function known with its public diameter."""
    _REGISTRY[name] = (fn, diameter)


def registered(name: str) -> tuple[Callable, float]:
    return _REGISTRY[name]


register("vector_l2", vector_l2, 2.0)
register("vector_cosine", vector_cosine, 2.0)
