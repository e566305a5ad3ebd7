"""Fixed row contracts and the check that enforces them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_TYPES = {"long": T.LongType(), "int": T.IntegerType(), "double": T.DoubleType(), "string": T.StringType(), "boolean": T.BooleanType(), "longs": T.ArrayType(T.LongType())}

POI = "poi_id string, lat double, lon double, l1 string, l2 string, l3 string, open_h int, close_h int, popularity long"
TRAJ = "traj_id string, pos int, poi_id string, t int"
REGION = "region_id long, gs int, cx int, cy int, lvl int, node string, t_start int, t_end int, clat double, clon double, tmid double, n_poi long, under_full boolean"
EDGE = "src long, dst long"
WINDOW = "traj_id string, a int, b int, gram longs, kind string"
Z = "traj_id string, a int, b int, gram longs"
RELEASED = "traj_id string, pos int, poi_id string, t int, smoothed boolean, attempts int"
HOTSPOT = "granularity string, entity string, t_s int, t_e int, peak long"


def fields(spec: str) -> list[tuple[str, T.DataType]]:
    return [(name, _TYPES[kind]) for name, kind in (part.split() for part in spec.split(", "))]


def struct(spec: str) -> T.StructType:
    """The Spark schema of a contract."""
    return T.StructType([T.StructField(n, k) for n, k in fields(spec)])


def conform(df: DataFrame, spec: str, not_null: tuple[str, ...] = ()) -> DataFrame:
    """Cast and order the columns of a contract; missing columns raise, rows with a null or NaN key are rejected."""
    missing = [n for n, _ in fields(spec) if n not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
    out = df.select(*[F.col(n).cast(k).alias(n) for n, k in fields(spec)])
    kinds = dict(fields(spec))
    for name in not_null:
        out = out.where(F.col(name).isNotNull())
        if isinstance(kinds[name], T.DoubleType):
            out = out.where(~F.isnan(name))
    return out
