"""The data sets of the experiments on the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..config import Cfg
from ..functions import timeline
from ..functions.rng import uniform
from .io import table

#: Fixed values of the event city: its types in order and their opening hours (past 24 is past midnight).
TYPES = ("click", "error", "purchase", "signup", "view")
HOURS = {"click": (0, 24), "error": (4, 26), "purchase": (6, 24), "signup": (5, 23), "view": (0, 24)}
BOX = (40.70, -74.02, 0.10, 0.12)


def _number() -> Column:
    out = F.when(F.col("event_type") == TYPES[0], 0)
    for i, t in enumerate(TYPES[1:], 1):
        out = out.when(F.col("event_type") == t, i)
    return out


def visits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, user_id, ts, event_type, k, poi_id of every event; JSON is parsed on pruned columns only."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type", "value", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return e.withColumn("poi_id", F.concat_ws(":", "event_type", F.col("k").cast("string")))


def event_poi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event city's places, one row per (type, k), with position, tree path, hours and visits."""
    # events are counted before their JSON is read: there are few different ones
    seen = table(spark, sf_dir, "events").groupBy("event_type", "props").agg(F.count(F.lit(1)).alias("n"))
    seen = seen.withColumn("k", F.get_json_object("props", "$.k").cast("int")).withColumn("poi_id", F.concat_ws(":", "event_type", F.col("k").cast("string")))
    p = seen.groupBy("poi_id", "event_type", "k").agg(F.sum("n").alias("popularity"))
    e = _number()
    second = F.concat_ws("/", "event_type", F.floor(F.col("k") / 40).cast("string"))
    opens, closes = F.lit(None).cast("int"), F.lit(None).cast("int")
    for t, (o, c) in HOURS.items():
        opens, closes = F.when(F.col("event_type") == t, o).otherwise(opens), F.when(F.col("event_type") == t, c).otherwise(closes)
    return p.select(
        "poi_id", (F.lit(40.70) + F.lit(0.10) * ((37 * F.col("k") + 11 * e) % 101) / 100).alias("lat"), (F.lit(-74.02) + F.lit(0.12) * ((53 * F.col("k") + 29 * e) % 103) / 102).alias("lon"),
        F.col("event_type").alias("l1"), second.alias("l2"), F.concat_ws("/", second, F.floor(F.col("k") / 20).cast("string")).alias("l3"), opens.alias("open_h"), closes.alias("close_h"), "popularity",
    )


def to_traj(points: DataFrame, key: Column, t: Column, order: list[Column], min_len: int = 3, max_len: int = 8, tasks: int | None = None) -> DataFrame:
    """Trajectories (traj_id, pos, poi_id, t): one point per slot, the first in ``order``; other lengths are dropped.

    ``tasks``: deal by trajectory first, so that nothing that follows by trajectory is shuffled again."""
    p = points.select(key.alias("traj_id"), t.alias("t"), "poi_id", *[c.alias(f"o{i}") for i, c in enumerate(order)])
    p = p if tasks is None else p.repartition(tasks, "traj_id")
    first = W.partitionBy("traj_id", "t").orderBy(*[f"o{i}" for i in range(len(order))])
    one = p.withColumn("rn", F.row_number().over(first)).where("rn = 1")
    all_ = W.partitionBy("traj_id")
    kept = one.withColumn("len", F.count(F.lit(1)).over(all_)).where(F.col("len").between(min_len, max_len))
    return kept.select("traj_id", F.row_number().over(all_.orderBy("t")).cast("int").alias("pos"), "poi_id", F.col("t").cast("int").alias("t"))


def event_traj(spark: SparkSession, sf_dir: str, min_len: int = 3, max_len: int = 8, thinning: str = "earliest", seed: str = "7", gt_min: int = 10) -> DataFrame:
    """User-days of the event city; one point per slot is the earliest, or a seeded random one."""
    v = visits(spark, sf_dir)
    order = [F.col("ts"), F.col("event_id")] if thinning == "earliest" else [uniform(seed, F.col("event_id").cast("string"))]
    key = F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    return to_traj(v, key, timeline.slot(F.col("ts"), gt_min), order, min_len, max_len)


def event_days(spark: SparkSession, sf_dir: str, tasks: int, min_len: int = 3, max_len: int = 8, gt_min: int = 10) -> DataFrame:
    """``event_traj`` with one row per user-day (traj_id, len, seq array<struct<pos, poi_id, t>>).

    Events are dealt by user and day as they are read, few files or many; text is made and JSON read after that, and nothing
    is shuffled again.
    """
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type", "props", F.to_date("ts").alias("day")).repartition(tasks, "user_id", "day")
    one = e.groupBy("user_id", "day", timeline.slot(F.col("ts"), gt_min).alias("t")).agg(F.min(F.struct("ts", "event_id", "event_type", "props")).alias("m"))
    poi_id = F.concat_ws(":", "m.event_type", F.get_json_object("m.props", "$.k").cast("int").cast("string"))
    days = one.groupBy("user_id", "day").agg(F.array_sort(F.collect_list(F.struct("t", poi_id.alias("poi_id")))).alias("s")).where(F.size("s").between(min_len, max_len))
    seq = F.transform("s", lambda x, i: F.struct((i + 1).cast("int").alias("pos"), x["poi_id"].alias("poi_id"), x["t"].alias("t")))
    return days.select(F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("day", "yyyy-MM-dd")).alias("traj_id"), F.size("s").alias("len"), seq.alias("seq"))


def shopping_traj(spark: SparkSession, sf_dir: str, min_len: int = 3, max_len: int = 8) -> DataFrame:
    """Customer-months: one line per ship date, the place a part, the store a supplier."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_shipdate")
    j = line.join(o, line.l_orderkey == o.o_orderkey)
    key = F.concat_ws("|", F.col("o_custkey").cast("string"), F.date_format("l_shipdate", "yyyy-MM"))
    per = j.groupBy(key.alias("traj_id"), F.dayofmonth("l_shipdate").alias("t")).agg(F.min(F.struct("l_partkey", "l_suppkey")).alias("m"))
    all_ = W.partitionBy("traj_id")
    kept = per.withColumn("len", F.count(F.lit(1)).over(all_)).where(F.col("len").between(min_len, max_len))
    return kept.select("traj_id", F.row_number().over(all_.orderBy("t")).cast("int").alias("pos"), F.col("m.l_partkey").alias("poi_id"), F.col("m.l_suppkey").alias("store"), F.col("t").cast("int").alias("t"))


def shopping_stores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stores with a position by nation; every fifth is online and always reachable."""
    s, n = table(spark, sf_dir, "supplier"), table(spark, sf_dir, "nation")
    j = s.select("s_suppkey", "s_nationkey").join(F.broadcast(n.select("n_nationkey", "n_regionkey")), F.col("s_nationkey") == F.col("n_nationkey"))
    return j.select(
        F.col("s_suppkey").alias("store"), (F.lit(-40.0) + 20 * F.col("n_regionkey") + 2 * F.floor(F.col("n_nationkey") / 5)).alias("lat"),
        (F.lit(-150.0) + 12 * F.col("n_nationkey")).alias("lon"), (F.col("s_suppkey") % 5 == 0).alias("online"),
    )


def campus_poi(spark: SparkSession, sf_dir: str, size: int = 262) -> DataFrame:
    """Buildings of a 2 km square in nine categories, from the first parts by key."""
    p = table(spark, sf_dir, "part").select("p_partkey").where(F.col("p_partkey") < size)
    k = F.col("p_partkey")
    node = F.concat(F.lit("c"), (k % 9).cast("string"))
    return p.select(
        k.cast("string").alias("poi_id"), (F.lit(49.26) + F.lit(0.018) * ((37 * k) % 101) / 100).alias("lat"), (F.lit(-123.25) + F.lit(0.027) * ((53 * k) % 103) / 102).alias("lon"),
        node.alias("l1"), F.concat_ws("/", node, F.lit("0")).alias("l2"), F.concat_ws("/", node, F.lit("0"), F.lit("0")).alias("l3"),
        F.when(k % 9 == 0, 6).otherwise(0).alias("open_h"), F.when(k % 9 == 0, 23).otherwise(24).alias("close_h"), (1 + k % 50).cast("long").alias("popularity"),
    )


def popularity_by_hour(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Visits per place and hour."""
    return visits(spark, sf_dir).groupBy("poi_id", F.hour("ts").alias("hour")).agg(F.count(F.lit(1)).alias("visits"))


def text_mentions(spark: SparkSession, sf_dir: str, tokens: tuple[str, ...] = ("the", "of", "de", "der", "la")) -> DataFrame:
    """How often listed words occur in comments, by language: a popularity signal from text."""
    d = table(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower("text"), " ")).alias("token"))
    return d.where(F.col("token").isin(*tokens)).groupBy("lang", "token").agg(F.count(F.lit(1)).alias("n"))


def snap(points: DataFrame, poi: DataFrame, most_m: float = 100.0) -> DataFrame:
    """Points (id, lat, lon) with their nearest place within ``most_m`` metres, ties by id; others are dropped.

    Places are broadcast over the 3 x 3 neighbouring cells, so each point meets only places near it.
    """
    from ..functions.distance import haversine_km

    step = most_m / 111_000.0
    cell_y, cell_x = F.floor(F.col("lat") / step), F.floor(F.col("lon") / (step * 2))
    p = poi.select("poi_id", F.col("lat").alias("p_lat"), F.col("lon").alias("p_lon"), F.floor(F.col("lat") / step).alias("cy"), F.floor(F.col("lon") / (step * 2)).alias("cx"))
    around = points.withColumn("cy", F.explode(F.array(*[cell_y + d for d in (-1, 0, 1)]))).withColumn("cx", F.explode(F.array(*[cell_x + d for d in (-1, 0, 1)])))
    near = around.join(p, ["cy", "cx"]).withColumn("m", F.round(1000 * haversine_km(F.col("lat"), F.col("lon"), F.col("p_lat"), F.col("p_lon")), 6)).where(F.col("m") <= most_m)
    best = near.groupBy("id").agg(F.min(F.struct("m", "poi_id")).alias("b"))
    return best.select("id", F.col("b.poi_id").alias("poi_id"), F.col("b.m").alias("m"))


def cfg_for(name: str) -> Cfg:
    """Default settings of a scenario."""
    return {"campus": Cfg(speed_kmh=4.0), "shopping": Cfg(gt_min=1440)}.get(name, Cfg())
