"""Registered queries of the engine and, where SQL can say it, their DuckDB twins.

Twins are built from shared common table expressions; Spark and SQL draw the same numbers from md5 keys.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .config import Cfg
from .functions import distance as D
from .functions import timeline
from .functions.rng import uniform, uniform_sql
from .operators import audit, budget, catalog, cost, expmech, globalmech, hotspots, metrics, ngrams, ops, perturb, reach, rebuild, regions
from .sources import scenarios as S
from .sources.io import staged, table

#: The twins' seed is public; a release draws a secret one.
CFG = Cfg(seed="7")
SEED = CFG.seed
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a function under its name, with its twin."""

    def add(fn: Query) -> Query:
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLES[fn.__name__] = sql
        return fn

    return add


# ---------------------------------------------------------------- shared SQL

_E = "CASE event_type " + " ".join(f"WHEN '{t}' THEN {i}" for i, t in enumerate(S.TYPES)) + " END"
_OPEN = "CASE event_type " + " ".join(f"WHEN '{t}' THEN {o}" for t, (o, _) in S.HOURS.items()) + " END"
_CLOSE = "CASE event_type " + " ".join(f"WHEN '{t}' THEN {c}" for t, (_, c) in S.HOURS.items()) + " END"
HAV = D.haversine_sql
CTE = {
    "visits": (
        [],
        """SELECT event_id, user_id, ts, event_type, value, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k,
           event_type || ':' || json_extract_string(props, '$.k') AS poi_id FROM events""",
    ),
    "poi": (
        ["visits"],
        f"""SELECT poi_id, 40.70::DOUBLE + 0.10::DOUBLE * ((37*k + 11*({_E})) % 101) / 100.0::DOUBLE AS lat,
            -74.02::DOUBLE + 0.12::DOUBLE * ((53*k + 29*({_E})) % 103) / 102.0::DOUBLE AS lon,
            event_type AS l1, event_type || '/' || (k // 40) AS l2, event_type || '/' || (k // 40) || '/' || (k // 20) AS l3,
            {_OPEN} AS open_h, {_CLOSE} AS close_h, count(*)::BIGINT AS popularity FROM visits GROUP BY poi_id, event_type, k""",
    ),
    "open_hours": (["poi"], "SELECT p.*, h.hour FROM poi p, (SELECT unnest(range(24))::INTEGER AS hour) h WHERE (hour >= open_h AND hour < close_h) OR (hour + 24 >= open_h AND hour + 24 < close_h)"),
    "slotted": (
        ["visits"],
        """SELECT user_id || '|' || strftime(ts, '%Y-%m-%d') AS traj_id, (hour(ts)*60 + minute(ts)) // 10 AS t, poi_id FROM visits
           QUALIFY row_number() OVER (PARTITION BY user_id, ts::DATE, (hour(ts)*60 + minute(ts)) // 10 ORDER BY ts, event_id) = 1""",
    ),
    "traj": (
        ["slotted"],
        """SELECT traj_id, row_number() OVER (PARTITION BY traj_id ORDER BY t)::INTEGER AS pos, poi_id, t::INTEGER AS t
           FROM (SELECT *, count(*) OVER (PARTITION BY traj_id) AS n FROM slotted) WHERE n BETWEEN 3 AND 8""",
    ),
    "legs": (
        ["traj", "poi"],
        f"""SELECT *, {HAV('b_lat', 'b_lon', 'lat', 'lon')} AS km FROM (SELECT t.*, p.lat, p.lon, p.open_h, p.close_h, p.l1, lag(lat) OVER w AS b_lat,
            lag(lon) OVER w AS b_lon, lag(t) OVER w AS b_t FROM traj t JOIN poi p USING (poi_id) WINDOW w AS (PARTITION BY traj_id ORDER BY pos))""",
    ),
    "valid": (
        ["legs"],
        """SELECT traj_id, pos, poi_id, t FROM (SELECT *, min((coalesce(b_t IS NULL OR round(km, 9) <= (t - b_t) * 10 * 8.0 / 60, false)
            AND ((t*10//60 >= open_h AND t*10//60 < close_h) OR (t*10//60 + 24 >= open_h AND t*10//60 + 24 < close_h)))::INT)
            OVER (PARTITION BY traj_id) AS ok FROM legs) WHERE ok = 1""",
    ),
    # every step of the merging ladder: (grid, hours, level)
    "cells": (
        ["open_hours"],
        "SELECT poi_id, hour, l1, l2, l3, " + ", ".join(f"greatest(0, least({g - 1}, floor((lon + 74.02) / 0.12 * {g})))::INTEGER AS cx_{g}, greatest(0, least({g - 1}, floor((lat - 40.70) / 0.10 * {g})))::INTEGER AS cy_{g}" for g in (4, 2, 1)) + " FROM open_hours",
    ),
}
KEYSQL = "gs, cx, cy, width, t_start, lvl, node"


def _ladder_sql(cfg: Cfg, tag: str) -> tuple[dict, str]:
    """CTEs of the merging steps; the last name holds (key, poi_id, hour, under_full) of all members."""
    out, frontier, parts = {}, "cells", []
    steps = regions.ladder(cfg)
    for i, (gs, width, level) in enumerate(steps):
        last = i == len(steps) - 1
        keyed, size, joined = f"{tag}k{i}", f"{tag}s{i}", f"{tag}j{i}"
        out[keyed] = ([frontier], f"SELECT *, {gs} AS gs, cx_{gs} AS cx, cy_{gs} AS cy, {width} AS width, hour // {width} * {width} AS t_start, {level} AS lvl, l{level} AS node FROM {frontier}")
        out[size] = ([keyed], f"SELECT {KEYSQL}, count(DISTINCT poi_id) AS size_ FROM {keyed} GROUP BY ALL")
        out[joined] = ([keyed, size], f"SELECT * FROM {keyed} JOIN {size} USING ({KEYSQL})")
        parts.append(f"SELECT {KEYSQL}, poi_id, hour, size_ < {cfg.kappa} AS under_full FROM {joined}" + ("" if last else f" WHERE size_ >= {cfg.kappa}"))
        frontier = f"{tag}f{i}"
        out[frontier] = ([joined], f"SELECT poi_id, hour, l1, l2, l3, cx_4, cy_4, cx_2, cy_2, cx_1, cy_1 FROM {joined} WHERE size_ < {cfg.kappa}")
    out[f"{tag}members"] = ([f"{tag}j{i}" for i in range(len(steps))], " UNION ALL ".join(parts))
    out[f"{tag}regions"] = ([f"{tag}members"], f"SELECT {KEYSQL}, t_start + width AS t_end, count(DISTINCT poi_id)::BIGINT AS n_poi, bool_or(under_full) AS under_full FROM {tag}members GROUP BY {KEYSQL}")
    return out, f"{tag}members"


for _tag, _cfg in (("", CFG), ("small_", CFG.but(kappa=5)), ("tfirst_", CFG.but(merge_order=("time", "space", "category")))):
    CTE |= _ladder_sql(_cfg, _tag)[0]
CTE |= {
    "described": (
        ["regions", "members", "poi"],
        f"""SELECT r.*, s.clat, s.clon, s.set_id, ((t_start + t_end) / 2.0) % 24.0 AS tmid, (row_number() OVER (ORDER BY {KEYSQL}) - 1)::BIGINT AS region_id
            FROM regions r JOIN (SELECT {KEYSQL}, round(avg(lat), 9) AS clat, round(avg(lon), 9) AS clon, md5(string_agg(poi_id, ',' ORDER BY poi_id)) AS set_id
            FROM (SELECT DISTINCT {KEYSQL}, poi_id, lat, lon FROM members JOIN poi USING (poi_id)) GROUP BY {KEYSQL}) s USING ({KEYSQL})""",
    ),
    "numbered": (["members", "described"], f"SELECT region_id, set_id, poi_id, hour FROM members JOIN described USING ({KEYSQL})"),
    "sets": (["numbered"], "SELECT DISTINCT set_id, poi_id FROM numbered"),
    "set_gaps": (["sets", "poi"], f"SELECT a, b, round(min({HAV('a_lat', 'a_lon', 'b_lat', 'b_lon')}), 9) AS km FROM (SELECT s.set_id AS a, lat AS a_lat, lon AS a_lon FROM sets s JOIN poi USING (poi_id)), (SELECT s.set_id AS b, lat AS b_lat, lon AS b_lon FROM sets s JOIN poi USING (poi_id)) GROUP BY a, b"),
    "edges": (["described", "set_gaps"], "SELECT x.region_id AS src, y.region_id AS dst FROM set_gaps g JOIN described x ON x.set_id = g.a JOIN described y ON y.set_id = g.b WHERE y.t_end*6 - 1 - x.t_start*6 >= 1 AND km <= (y.t_end*6 - 1 - x.t_start*6) * 10 * 8.0 / 60"),
    "encoded": (["valid", "numbered"], "SELECT v.traj_id, v.pos, v.t, v.poi_id, m.region_id FROM valid v LEFT JOIN (SELECT poi_id, hour, min(region_id) AS region_id FROM numbered GROUP BY ALL) m ON m.poi_id = v.poi_id AND m.hour = v.t*10//60"),
    "packed": (["encoded"], "SELECT traj_id, list(region_id ORDER BY pos) AS seq, count(*)::INTEGER AS len FROM encoded GROUP BY traj_id"),
    # a second, seeded set that stands for a released one: every place moved to a drawn place, times as they are
    "released": (
        ["valid", "poi"],
        f"""SELECT traj_id, pos, poi_id, t FROM (SELECT v.traj_id, v.pos, q.poi_id, v.t, row_number() OVER (PARTITION BY v.traj_id, v.pos
            ORDER BY {uniform_sql("'7'", "v.traj_id", "v.pos::VARCHAR", "q.poi_id")}, q.poi_id) AS rn FROM valid v JOIN poi p ON p.poi_id = v.poi_id JOIN poi q ON q.l2 = p.l2) WHERE rn = 1""",
    ),
    "errors": (
        ["valid", "released", "poi"],
        f"""SELECT a.traj_id, a.pos, least(abs(a.t - b.t) * 10 / 60.0, 12.0)::DOUBLE AS d_t, {D.category_sql('p.l3', 'q.l3')} AS d_c, round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 9) AS d_s
            FROM valid a JOIN released b USING (traj_id, pos) JOIN poi p ON p.poi_id = a.poi_id JOIN poi q ON q.poi_id = b.poi_id""",
    ),
    # toy space: nations as regions, a nation may be followed by one of its or the next world region
    "toy": ([], "SELECT n_nationkey::BIGINT AS node, n_regionkey AS grp, (n_nationkey % 5)::DOUBLE AS x, (n_nationkey // 5)::DOUBLE AS y FROM nation"),
    "toy_d": (["toy"], "SELECT a.node AS src, b.node AS dst, sqrt((a.x-b.x)*(a.x-b.x) + (a.y-b.y)*(a.y-b.y)) AS d FROM toy a, toy b"),
    "toy_edges": (["toy"], "SELECT a.node AS src, b.node AS dst FROM toy a JOIN toy b ON b.grp = a.grp OR b.grp = (a.grp + 1) % 5"),
    "toy_pairs": (["toy_d"], "SELECT src AS input, dst AS cand, d AS dist FROM toy_d"),
    "toy_bigrams": (["toy_edges", "toy_d"], "SELECT i.src || '>' || i.dst AS input, o.src || '>' || o.dst AS cand, p.d + q.d AS dist FROM toy_edges i, toy_edges o, toy_d p, toy_d q WHERE p.src = i.src AND p.dst = o.src AND q.src = i.dst AND q.dst = o.dst"),
    # two votes for every point of the valid trajectories on the toy space
    "toy_votes": (["valid"], "SELECT traj_id, pos, (length(poi_id) * 7 + t + pos * 3 + v) % 25 AS region_id FROM valid, (SELECT unnest([0, 11]) AS v)"),
    "toy_nodes": (["toy_votes", "toy_d"], "SELECT traj_id, pos, dst AS region_id, round(sum(k * d), 6) AS err FROM (SELECT traj_id, pos, region_id, count(*) AS k FROM toy_votes GROUP BY ALL) JOIN toy_d ON src = region_id GROUP BY traj_id, pos, dst"),
    "toy_bierr": (["toy_nodes", "toy_edges"], "SELECT a.traj_id, a.pos, e.src, e.dst, round(a.err + b.err, 6) AS err FROM toy_nodes a JOIN toy_edges e ON e.src = a.region_id JOIN toy_nodes b ON b.traj_id = a.traj_id AND b.pos = a.pos + 1 AND b.region_id = e.dst"),
    "shop": (
        [],
        """SELECT traj_id, row_number() OVER (PARTITION BY traj_id ORDER BY t)::INTEGER AS pos, p AS poi_id, s AS store, t FROM (SELECT *, count(*) OVER (PARTITION BY traj_id) AS n FROM
           (SELECT o_custkey || '|' || strftime(l_shipdate, '%Y-%m') AS traj_id, day(l_shipdate)::INTEGER AS t, min((l_partkey, l_suppkey)) AS m, m[1] AS p, m[2] AS s
            FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2)) WHERE n BETWEEN 3 AND 8""",
    ),
}
for _g in ("poi", "grid4", "l1"):
    _ent = {"poi": "poi_id", "l1": "l1", "grid4": "greatest(0, least(3, floor((lat - 40.70) / 0.10 * 4)))::INTEGER || ':' || greatest(0, least(3, floor((lon + 74.02) / 0.12 * 4)))::INTEGER"}[_g]
    for _set in ("traj", "released"):
        _eta = {"poi": 1, "grid4": 2, "l1": 5}[_g]
        CTE[f"hot_{_g}_{_set}"] = (
            [_set, "poi"],
            f"""SELECT '{_g}' AS granularity, entity, min(slot)::INTEGER AS t_s, (max(slot) + 1)::INTEGER AS t_e, max(n)::BIGINT AS peak FROM (SELECT *, slot - row_number() OVER (PARTITION BY entity ORDER BY slot) AS island
                FROM (SELECT {_ent} AS entity, t * 10 // 60 AS slot, count(DISTINCT traj_id) AS n FROM {_set} JOIN poi USING (poi_id) GROUP BY ALL) WHERE n > {_eta}) GROUP BY entity, island""",
        )


def sql(body: str, *names: str) -> str:
    """A statement with the expressions it needs, in order; each is made once."""
    done: list[str] = []

    def need(name: str) -> None:
        for n in CTE[name][0]:
            need(n)
        if name not in done:
            done.append(name)

    for n in names:
        need(n)
    return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({CTE[n][1]})" for n in done) + f"\n{body}" if done else body


# ---------------------------------------------------------------- public side


@query(sql("SELECT poi_id, lat, lon, l1, l2, l3, popularity FROM poi", "poi"))
def poi_catalog(spark, d):
    return catalog.build(S.event_poi(spark, d)).drop("open_h", "close_h")


@query(sql("SELECT poi_id, popularity FROM poi ORDER BY popularity DESC, poi_id LIMIT 100", "poi"))
def wk_top_places(spark, d):
    return catalog.top_popular(S.event_poi(spark, d), 100).select("poi_id", "popularity")


@query(sql("SELECT poi_id, hour FROM open_hours", "open_hours"))
def poi_hours_open(spark, d):
    return catalog.open_hours(S.event_poi(spark, d)).select("poi_id", "hour")


@query("SELECT DISTINCT ((hour(ts)*60 + minute(ts)) // 10)::INTEGER AS slot, ((hour(ts)*60 + minute(ts)) // 10 * 10)::INTEGER AS minute FROM events")
def time_slots(spark, d):
    """The slots of the day in which events fall, with their first minute."""
    return timeline.seen(table(spark, d, "events"), 10)


@query(sql("SELECT * FROM traj", "traj"))
def traj_long(spark, d):
    return S.event_traj(spark, d)


@query(sql("SELECT len, count(*)::BIGINT AS n FROM (SELECT count(*)::INTEGER AS len FROM traj GROUP BY traj_id) GROUP BY len", "traj"))
def traj_packed_lengths(spark, d):
    return perturb.packed(S.event_traj(spark, d), "poi_id", "t").groupBy("len").agg(F.count(F.lit(1)).alias("n"))


@query(sql("SELECT count(*)::BIGINT AS points, count(DISTINCT traj_id)::BIGINT AS days FROM slotted", "slotted"))
def traj_dedup(spark, d):
    return S.event_traj(spark, d, 1, 10**6).agg(F.count(F.lit(1)).alias("points"), F.countDistinct("traj_id").alias("days"))


def _valid(spark, d, cfg=CFG) -> DataFrame:
    return reach.valid_only(S.event_traj(spark, d), S.event_poi(spark, d), cfg)


@query(sql("SELECT traj_id, count(*)::BIGINT AS len FROM valid GROUP BY traj_id", "valid"))
def traj_feasible(spark, d):
    return _valid(spark, d).groupBy("traj_id").agg(F.count(F.lit(1)).alias("len"))


@query(sql("SELECT poi_id, hour(ts)::INTEGER AS hour, count(*)::BIGINT AS visits FROM visits GROUP BY ALL", "visits"))
def popularity_by_hour(spark, d):
    return S.popularity_by_hour(spark, d)


@query("SELECT event_type AS l1, " + ", ".join(f"round(quantile_cont(value, {q}), 6) AS p{int(q * 100)}" for q in (0.25, 0.5, 0.75)) + " FROM events GROUP BY 1")
def dwell_quantiles(spark, d):
    e = table(spark, d, "events")
    return e.groupBy(F.col("event_type").alias("l1")).agg(*[F.round(F.percentile("value", F.lit(q)), 6).alias(f"p{int(q * 100)}") for q in (0.25, 0.5, 0.75)])


@query(sql(" UNION ALL ".join(f"SELECT DISTINCT poi_id, {g} AS gs, cx_{g} AS cx, cy_{g} AS cy FROM cells" for g in (4, 2, 1)), "cells"))
def grid_cells(spark, d):
    p = S.event_poi(spark, d)
    parts = []
    for g in (4, 2, 1):
        cy, cx = regions.grid_cell(F.col("lat"), F.col("lon"), g)
        parts.append(F.struct(F.lit(g).alias("gs"), cx.alias("cx"), cy.alias("cy")))
    return p.select("poi_id", F.explode(F.array(*parts)).alias("c")).select("poi_id", "c.*")


@query(sql("SELECT cx_4 AS cx, cy_4 AS cy, l3 AS node, hour, poi_id FROM cells", "cells"))
def stc_assign(spark, d):
    return regions.assign(S.event_poi(spark, d), CFG).select(F.col("cx_4").alias("cx"), F.col("cy_4").alias("cy"), F.col("l3").alias("node"), "hour", "poi_id")


@query(sql("SELECT cx_4 AS cx, cy_4 AS cy, l3 AS node, hour, count(DISTINCT poi_id)::BIGINT AS n_poi FROM cells GROUP BY ALL", "cells"))
def stc_count(spark, d):
    return stc_assign(spark, d).groupBy("cx", "cy", "node", "hour").agg(F.countDistinct("poi_id").alias("n_poi"))


_REGION_COLUMNS = "gs, cx, cy, lvl, node, t_start, t_end, n_poi, under_full"


def _merged(spark, d, cfg=CFG):
    return regions.merge(regions.assign(S.event_poi(spark, d), cfg), cfg)


@query(sql(f"SELECT {_REGION_COLUMNS} FROM regions", "regions"))
def stc_merge_full(spark, d):
    return _merged(spark, d)[0].select(*_REGION_COLUMNS.split(", "))


@query(sql(f"SELECT {_REGION_COLUMNS} FROM small_regions", "small_regions"))
def stc_merge_space(spark, d):
    return _merged(spark, d, CFG.but(kappa=5))[0].select(*_REGION_COLUMNS.split(", "))


@query(sql(f"SELECT {_REGION_COLUMNS} FROM tfirst_regions", "tfirst_regions"))
def stc_merge_time(spark, d):
    return _merged(spark, d, CFG.but(merge_order=("time", "space", "category")))[0].select(*_REGION_COLUMNS.split(", "))


def _described(spark, d):
    poi = S.event_poi(spark, d)
    r, m = _merged(spark, d)
    r = staged(regions.describe(r, m, poi))
    return poi, r, m.join(F.broadcast(r.select(*regions.KEY, "region_id", "set_id")), regions.KEY)


@query(sql("SELECT region_id, round(clat, 6) AS clat, round(clon, 6) AS clon, tmid::DOUBLE AS tmid FROM described", "described"))
def region_centroid(spark, d):
    return _described(spark, d)[1].select("region_id", F.round("clat", 6).alias("clat"), F.round("clon", 6).alias("clon"), "tmid")


@query(sql(f"SELECT p.poi_id AS a, q.poi_id AS b, round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 6) AS km FROM poi p JOIN poi q ON p.l3 = q.l3 AND p.poi_id < q.poi_id", "poi"))
def dist_physical_pairs(spark, d):
    p = S.event_poi(spark, d).select("poi_id", "lat", "lon", "l3")
    q = p.select(F.col("poi_id").alias("b"), F.col("lat").alias("lat_b"), F.col("lon").alias("lon_b"), "l3")
    return p.join(q, "l3").where("poi_id < b").select(F.col("poi_id").alias("a"), "b", F.round(D.haversine_km(F.col("lat"), F.col("lon"), F.col("lat_b"), F.col("lon_b")), 6).alias("km"))


@query("SELECT a.h AS a, b.h AS b, least(abs(a.h - b.h), 12)::DOUBLE AS h FROM (SELECT DISTINCT hour(ts)::INTEGER AS h FROM events) a, (SELECT DISTINCT hour(ts)::INTEGER AS h FROM events) b")
def dist_time_pairs(spark, d):
    """Time distances between the hours in which events fall."""
    h = table(spark, d, "events").select(F.hour("ts").alias("a")).distinct()
    return h.join(F.broadcast(h.withColumnRenamed("a", "b"))).select("a", "b", D.time_h(F.col("a").cast("double"), F.col("b").cast("double")).alias("h"))


@query(sql(f"SELECT x.n AS a, y.n AS b, {D.category_sql('x.n', 'y.n')} AS d_c FROM (SELECT l1 AS n FROM poi UNION SELECT l2 FROM poi UNION SELECT l3 FROM poi) x, (SELECT l1 AS n FROM poi UNION SELECT l2 FROM poi UNION SELECT l3 FROM poi) y", "poi"))
def dist_category_pairs(spark, d):
    p = S.event_poi(spark, d)
    n = p.select(F.explode(F.array("l1", "l2", "l3")).alias("a")).distinct()
    return n.join(F.broadcast(n.withColumnRenamed("a", "b"))).select("a", "b", D.category(F.col("a"), F.col("b")).alias("d_c"))


@query(sql(f"SELECT x.region_id AS a, y.region_id AS b, round(sqrt(pow({HAV('x.clat', 'x.clon', 'y.clat', 'y.clon')}, 2) + pow(least(abs(x.tmid - y.tmid), 12.0), 2) + pow({D.category_sql('x.node', 'y.node')}, 2)), 6) AS d FROM described x, described y", "described"))
def dist_combined_pairs(spark, d):
    _, r, _ = _described(spark, d)
    x = r.select(F.col("region_id").alias("a"), F.col("clat").alias("a1"), F.col("clon").alias("a2"), F.col("tmid").alias("a3"), F.col("node").alias("a4"))
    y = r.select(F.col("region_id").alias("b"), F.col("clat").alias("b1"), F.col("clon").alias("b2"), F.col("tmid").alias("b3"), F.col("node").alias("b4"))
    c = D.combined(D.haversine_km(F.col("a1"), F.col("a2"), F.col("b1"), F.col("b2")), D.time_h(F.col("a3"), F.col("b3")), D.category(F.col("a4"), F.col("b4")))
    return x.join(F.broadcast(y)).select("a", "b", F.round(c, 6).alias("d"))


_THETA = CFG.speed_kmh * CFG.gt_min / 60


@query(sql(f"SELECT p.poi_id AS a, q.poi_id AS b, round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 6) AS km FROM poi p JOIN poi q ON p.poi_id <> q.poi_id WHERE round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 6) <= {_THETA}", "poi"))
def reach_poi_pairs(spark, d):
    return reach.pairs(S.event_poi(spark, d), _THETA)


def _edges(spark, d, cfg=CFG):
    poi, r, m = _described(spark, d)
    return r, m, reach.region_edges(r, staged(reach.set_gaps(reach.place_sets(m), poi)), cfg)


@query(sql("SELECT src, dst FROM edges", "edges"))
def region_bigrams(spark, d):
    return _edges(spark, d)[2]


@query(sql("SELECT 3 AS n, sum(a.k * b.k)::DOUBLE AS n_grams FROM (SELECT dst AS r, count(*) AS k FROM edges GROUP BY 1) a JOIN (SELECT src AS r, count(*) AS k FROM edges GROUP BY 1) b USING (r)", "edges"))
def trigram_count(spark, d):
    r, _, e = _edges(spark, d)
    return ngrams.count_paths(r, staged(e), 3)


@query(sql("SELECT n_poi, round(log10(n_poi) * l + (lgamma(97) - lgamma(l + 1) - lgamma(97 - l)) / ln(10) + (l - 1) * log10(0.2), 6) AS log10_size FROM (SELECT count(*)::INTEGER AS n_poi FROM poi), (SELECT DISTINCT count(*)::INTEGER AS l FROM traj GROUP BY traj_id)", "poi", "traj"))
def search_space_size(spark, d):
    """The outputs that the catalog allows, for every length of the given trajectories."""
    places = S.event_poi(spark, d).agg(F.count(F.lit(1)).cast("int").alias("n_poi"))
    lengths = S.event_traj(spark, d).groupBy("traj_id").agg(F.count(F.lit(1)).cast("int").alias("len")).select("len").distinct()
    size = cost.log10_space(F.col("n_poi"), F.col("len"), 15, 0.2)
    return lengths.join(F.broadcast(places)).select("n_poi", F.round(size, 6).alias("log10_size"))


@query(sql(f"""SELECT src, dst, side FROM (SELECT p.poi_id AS src, q.poi_id AS dst, CASE WHEN round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 6) <= 0.5 THEN 'both' ELSE 'new' END AS side
    FROM poi p JOIN poi q ON p.poi_id <> q.poi_id AND round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 6) <= 1.0) WHERE side = 'new'""", "poi"))
def edge_delta_setops(spark, d):
    poi = S.event_poi(spark, d)
    old, new = (reach.pairs(poi, km).select(F.col("a").alias("src"), F.col("b").alias("dst")) for km in (0.5, 1.0))
    return ops.set_delta(old, new)


# ---------------------------------------------------------------- windows and budget


def _encoded(spark, d):
    _, _, m = _described(spark, d)
    return perturb.encode(_valid(spark, d), m)


@query(sql("SELECT traj_id, pos, region_id FROM encoded", "encoded"))
def encode_regions(spark, d):
    return _encoded(spark, d).select("traj_id", "pos", "region_id")


def _rows(spark, d):
    p = perturb.packed(_encoded(spark, d), "region_id")
    return p.select("traj_id", F.transform("seq", lambda x: x["region_id"]).alias("seq"))


_JOINED = "array_to_string(seq[a:b], '>')"


@query(sql(f"SELECT traj_id, a, b, {_JOINED} AS gram FROM (SELECT *, (a + 1)::INTEGER AS b FROM (SELECT *, unnest(range(1, len))::INTEGER AS a FROM packed))", "packed"))
def windows_main(spark, d):
    w = perturb.windows(_rows(spark, d), "seq", 2)
    return w.select("traj_id", "a", "b", F.array_join(F.transform("gram", lambda x: x.cast("string")), ">").alias("gram"))


@query(sql("SELECT traj_id, 1 AS a, 1 AS b, seq[1]::VARCHAR AS gram, 'prefix' AS kind FROM packed UNION ALL SELECT traj_id, len, len, seq[len]::VARCHAR, 'suffix' FROM packed", "packed"))
def windows_ends(spark, d):
    w = perturb.end_windows(_rows(spark, d), "seq", 2)
    return w.select("traj_id", "a", "b", F.array_join(F.transform("gram", lambda x: x.cast("string")), ">").alias("gram"), "kind")


@query(sql("SELECT unnest([1, 2, 3])::INTEGER AS n, 0::BIGINT AS bad_positions"))
def window_coverage(spark, d):
    rows = staged(_rows(spark, d))
    out = None
    for n in (1, 2, 3):
        one = audit.coverage(perturb.all_windows(rows, "seq", n), n).agg(F.count(F.lit(1)).alias("bad_positions")).select(F.lit(n).alias("n"), "bad_positions")
        out = one if out is None else out.unionByName(one)
    return out


@query(sql("SELECT traj_id, (len + 1)::BIGINT AS draws, 5.0::DOUBLE AS total FROM packed", "packed"))
def budget_ledger(spark, d):
    rows = _rows(spark, d)
    w = perturb.all_windows(rows, "seq", 2).join(rows.select("traj_id", F.size("seq").alias("len")), "traj_id")
    return budget.ledger(w.withColumn("eps", budget.split(F.col("len"), CFG, "hier")), ["traj_id"])


# ---------------------------------------------------------------- the mechanism on a toy space


def _toy(spark, d):
    n = table(spark, d, "nation")
    k = F.col("n_nationkey")
    return n.select(k.cast("long").alias("node"), F.col("n_regionkey").alias("grp"), (k % 5).cast("double").alias("x"), F.floor(k / 5).cast("double").alias("y"))


def _toy_d(spark, d):
    a = _toy(spark, d)
    b = a.select(F.col("node").alias("dst"), F.col("x").alias("x2"), F.col("y").alias("y2"))
    return a.join(F.broadcast(b)).select(F.col("node").alias("src"), "dst", F.sqrt((F.col("x") - F.col("x2")) ** 2 + (F.col("y") - F.col("y2")) ** 2).alias("d"))


def _toy_edges(spark, d):
    a = _toy(spark, d)
    b = a.select(F.col("node").alias("dst"), F.col("grp").alias("g2"))
    return a.join(F.broadcast(b), (F.col("g2") == F.col("grp")) | (F.col("g2") == (F.col("grp") + 1) % 5)).select(F.col("node").alias("src"), "dst")


def _toy_pairs(spark, d):
    return _toy_d(spark, d).select(F.col("src").alias("input"), F.col("dst").alias("cand"), F.col("d").alias("dist"))


def _toy_bigrams(spark, d):
    e, t = _toy_edges(spark, d), _toy_d(spark, d)
    i = e.select(F.col("src").alias("i1"), F.col("dst").alias("i2"))
    o = e.select(F.col("src").alias("o1"), F.col("dst").alias("o2"))
    p = t.select(F.col("src").alias("i1"), F.col("dst").alias("o1"), F.col("d").alias("d1"))
    q = t.select(F.col("src").alias("i2"), F.col("dst").alias("o2"), F.col("d").alias("d2"))
    j = i.join(F.broadcast(o)).join(F.broadcast(p), ["i1", "o1"]).join(F.broadcast(q), ["i2", "o2"])
    return j.select(F.concat_ws(">", "i1", "i2").alias("input"), F.concat_ws(">", "o1", "o2").alias("cand"), (F.col("d1") + F.col("d2")).alias("dist"))


_DIAM = 5.656854249492381  # of the toy grid, corner to corner
_LAW = "SELECT *, exp(-{e} * dist / (2 * {dl})) / sum(exp(-{e} * dist / (2 * {dl}))) OVER (PARTITION BY input) AS p FROM {src}"


@query(sql(f"SELECT input, cand AS output, round(p, 6) AS p FROM ({_LAW.format(e=2.0, dl=2 * _DIAM, src='toy_bigrams')})", "toy_bigrams"))
def em_law_bigram(spark, d):
    law = expmech.law(_toy_bigrams(spark, d), ["input"], 2.0, 2 * _DIAM)
    return law.select("input", F.col("cand").alias("output"), F.round("p", 6).alias("p"))


@query(sql(f"SELECT eps, round(worst, 6) AS worst, round(exp(eps), 6) AS bound, worst <= exp(eps) AS ok FROM (SELECT eps, max(r) AS worst FROM (SELECT eps, cand, max(p) / min(p) AS r FROM (SELECT eps, cand, exp(-eps * dist / (2 * {2 * _DIAM})) / sum(exp(-eps * dist / (2 * {2 * _DIAM}))) OVER (PARTITION BY eps, input) AS p FROM toy_bigrams, (SELECT unnest([0.1::DOUBLE, 1.0, 5.0]) AS eps)) GROUP BY ALL) GROUP BY eps)", "toy_bigrams"))
def em_ratio_audit(spark, d):
    pairs, out = staged(_toy_bigrams(spark, d)), None
    for e in (0.1, 1.0, 5.0):
        one = audit.ratio_bound(expmech.law(pairs, ["input"], e, 2 * _DIAM), e).select(F.lit(e).alias("eps"), F.round("worst", 6).alias("worst"), F.round("bound", 6).alias("bound"), "ok")
        out = one if out is None else out.unionByName(one)
    return out


def _keyed(spark, d):
    """Many draws: every valid point asks for its toy neighbour."""
    v = _valid(spark, d).select(F.concat_ws("#", "traj_id", F.col("pos").cast("string")).alias("key"), (F.col("t") % 25).cast("long").alias("input"))
    return v.join(F.broadcast(_toy_pairs(spark, d)), "input").select("key", "cand", "dist")


_KEYED = "(SELECT traj_id || '#' || pos AS key, cand, dist FROM valid JOIN toy_pairs ON input = t % 25)"
_U = uniform_sql("'7'", "key", "cand::VARCHAR")


@query(sql(f"SELECT key, arg_max(cand, s) AS chosen FROM (SELECT *, -4.0 * dist / (2 * {_DIAM}) - ln(-ln({_U})) AS s FROM {_KEYED}) GROUP BY key", "valid", "toy_pairs"))
def em_draw_gumbel(spark, d):
    return expmech.draw_gumbel(_keyed(spark, d), ["key"], 4.0, _DIAM, SEED)


@query(sql(f"SELECT key, coalesce(min(CASE WHEN round(cum, 12) >= u THEN cand END), max(cand)) AS chosen FROM (SELECT key, cand, sum(p) OVER (PARTITION BY key ORDER BY cand ROWS UNBOUNDED PRECEDING) AS cum, {uniform_sql(chr(39) + '7' + chr(39), 'key')} AS u FROM (SELECT *, exp(-4.0 * dist / (2 * {_DIAM})) / sum(exp(-4.0 * dist / (2 * {_DIAM}))) OVER (PARTITION BY key) AS p FROM {_KEYED})) GROUP BY key", "valid", "toy_pairs"))
def em_draw_cdf(spark, d):
    return expmech.draw_cdf(_keyed(spark, d), ["key"], 4.0, _DIAM, SEED)


@query(sql(f"SELECT key, arg_max(cand, s) AS chosen FROM (SELECT *, -4.0 * dist / (2 * {_DIAM}) - ln({uniform_sql(chr(39) + '7' + chr(39), 'key', 'cand::VARCHAR', chr(39) + 'flip' + chr(39))}) AS s FROM {_KEYED}) GROUP BY key", "valid", "toy_pairs"))
def flip_draw(spark, d):
    return expmech.draw_flip(_keyed(spark, d), ["key"], 4.0, _DIAM, SEED)


@query(sql(f"SELECT key, arg_max(cand, s) AS chosen FROM (SELECT *, -4.0 * dist / (2 * {_DIAM}) - ln(-ln({_U})) AS s FROM {_KEYED} WHERE {uniform_sql(chr(39) + '7' + chr(39), chr(39) + 'sample' + chr(39), 'cand::VARCHAR')} < 0.5) GROUP BY key", "valid", "toy_pairs"))
def subsample_draw(spark, d):
    return expmech.draw_subsample(_keyed(spark, d), ["key"], 4.0, _DIAM, SEED, 0.5)


#: The whole-trajectory mechanism on a toy: every rising sequence of three (node, slot of four) pairs along the edges
#: is an output; one input stays at each node. A trajectory's distance is the sum of grid distance and slots apart.
_ALL_DELTA, _ALL_EPS, _ALL_OUT = 3 * (_DIAM + 3), 40.0, 25 * 10 * 10 * 4
_STEP = "({b}.node % 5 = {a}.node % 5 OR {b}.node % 5 = ({a}.node % 5 + 1) % 5) AND {b}.t > {a}.t"
_APART = "sqrt(pow(i.node % 5 - {o}.node % 5, 2) + pow(i.node // 5 - {o}.node // 5, 2)) + abs({n} - {o}.t)"
CTE["toy_points"] = (["toy"], "SELECT node, t FROM toy, (SELECT unnest(range(4)) AS t)")
CTE["toy_all"] = (
    ["toy_points", "toy"],
    f"""SELECT i.node AS input, concat(a.node, '@', a.t, '>', b.node, '@', b.t, '>', c.node, '@', c.t) AS cand, {_APART.format(o='a', n=0)} + {_APART.format(o='b', n=1)} + {_APART.format(o='c', n=2)} AS dist
        FROM toy i, toy_points a JOIN toy_points b ON {_STEP.format(a='a', b='b')} JOIN toy_points c ON {_STEP.format(a='b', b='c')}""",
)


def _toy_all(spark, d):
    toy = _toy(spark, d).select("node")
    points = toy.select("node", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("t"))

    def follows(a, b):
        return ((b["node"] % 5 == a["node"] % 5) | (b["node"] % 5 == (a["node"] % 5 + 1) % 5)) & (b["t"] > a["t"])

    inputs = toy.select(F.col("node").alias("input"), F.transform(F.sequence(F.lit(0), F.lit(2)), lambda t: F.struct(F.col("node").alias("node"), t.alias("t"))).alias("points"))
    return inputs, globalmech.enumerate_outputs(points, 3, follows)


def _toy_apart(x, y):
    return F.sqrt(F.pow(x["node"] % 5 - y["node"] % 5, 2) + F.pow(F.floor(x["node"] / 5) - F.floor(y["node"] / 5), 2)) + F.abs(x["t"] - y["t"])


def _global_form(name: str, form: str, score: str, kept: str):
    def run(spark, d):
        return globalmech.run(*_toy_all(spark, d), _toy_apart, _ALL_EPS, _ALL_DELTA, SEED, form, 0.5)

    run.__name__ = name
    return query(sql(f"SELECT input, arg_max(cand, -{_ALL_EPS} * dist / (2 * {_ALL_DELTA}) - {score}) AS chosen FROM toy_all {kept} GROUP BY input", "toy_all"))(run)


_ALL_U = uniform_sql("'7'", "input::VARCHAR", "cand")
_global_form("global_literal", "em", f"ln(-ln({_ALL_U}))", "")
_global_form("global_subsample", "subsample", f"ln(-ln({_ALL_U}))", f"WHERE {uniform_sql(chr(39) + '7' + chr(39), chr(39) + 'sample' + chr(39), 'cand')} < 0.5")
_global_form("global_flip", "flip", "ln(" + uniform_sql("'7'", "input::VARCHAR", "cand", "'flip'") + ")", "")
_ALL_TAIL = globalmech.tail_bound(3, _DIAM + 3, _ALL_EPS, _ALL_OUT, 1.0)


@query(sql(f"SELECT input, round(sum(CASE WHEN dist >= low + {_ALL_TAIL} THEN p ELSE 0 END), 9) AS mass, mass <= exp(-1.0) AS ok FROM (SELECT *, min(dist) OVER (PARTITION BY input) AS low FROM ({_LAW.format(e=_ALL_EPS, dl=_ALL_DELTA, src='toy_all')})) GROUP BY input", "toy_all"))
def global_tail(spark, d):
    """The whole-trajectory draw's mass past its loss bound."""
    law = expmech.law(globalmech.distances(*_toy_all(spark, d), _toy_apart), ["input"], _ALL_EPS, _ALL_DELTA)
    far = law.withColumn("low", F.min("dist").over(W.partitionBy("input"))).groupBy("input").agg(F.round(F.sum(F.when(F.col("dist") >= F.col("low") + _ALL_TAIL, F.col("p")).otherwise(0.0)), 9).alias("mass"))
    return far.select("input", "mass", (F.col("mass") <= float(math.exp(-1.0))).alias("ok"))


@query(sql(f"SELECT input, split_part(cand, '>', 1)::BIGINT AS first, round(sum(p), 6) AS p FROM ({_LAW.format(e=2.0, dl=2 * _DIAM, src='toy_bigrams')}) GROUP BY ALL", "toy_bigrams"))
def chain_first_marginal(spark, d):
    """The first node's law without any bigram made: node weight times the weights its edges lead to."""
    w = _toy_d(spark, d).withColumn("w", F.exp(-2.0 * F.col("d") / (2 * 2 * _DIAM)))
    e = _toy_edges(spark, d)
    after = w.select(F.col("src").alias("i2"), F.col("dst").alias("o2"), "w").join(F.broadcast(e.select(F.col("src").alias("o1"), F.col("dst").alias("o2"))), "o2").groupBy("i2", "o1").agg(F.sum("w").alias("beta"))
    i = e.select(F.col("src").alias("i1"), F.col("dst").alias("i2"))
    m = i.join(after, "i2").join(w.select(F.col("src").alias("i1"), F.col("dst").alias("o1"), F.col("w").alias("w1")), ["i1", "o1"])
    m = m.select(F.concat_ws(">", "i1", "i2").alias("input"), F.col("o1").alias("first"), (F.col("w1") * F.col("beta")).alias("m"))
    return m.select("input", "first", F.round(F.col("m") / F.sum("m").over(W.partitionBy("input")), 6).alias("p"))


@query(sql(f"""SELECT traj_id, pos, arg_max(q, s) AS poi_id FROM (SELECT v.traj_id, v.pos, q.poi_id AS q, -0.5 * round({HAV('p.lat', 'p.lon', 'q.lat', 'q.lon')}, 9) / 2 - ln(-ln({uniform_sql("'7'", "v.traj_id", "v.pos::VARCHAR", "q.poi_id")})) AS s
    FROM valid v JOIN poi p ON p.poi_id = v.poi_id, poi q) GROUP BY ALL""", "valid", "poi"))
def indep_free_draw(spark, d):
    """Every point alone over all places: a Gumbel argmax against the broadcast catalog, one aggregate."""
    p = S.event_poi(spark, d).select("poi_id", "lat", "lon")
    q = p.select(F.col("poi_id").alias("cand"), F.col("lat").alias("lat_b"), F.col("lon").alias("lon_b"))
    j = _valid(spark, d).join(F.broadcast(p), "poi_id").join(F.broadcast(q))
    pairs = j.select("traj_id", "pos", "cand", F.round(D.haversine_km(F.col("lat"), F.col("lon"), F.col("lat_b"), F.col("lon_b")), 9).alias("dist"))
    return expmech.draw_gumbel(pairs, ["traj_id", "pos"], 0.5, 1.0, SEED).withColumnRenamed("chosen", "poi_id")


# ---------------------------------------------------------------- rebuild on the toy space


def _toy_votes(spark, d):
    both = _valid(spark, d).select("traj_id", "pos", "poi_id", "t", F.explode(F.array(F.lit(0), F.lit(11))).alias("v"))
    return both.select("traj_id", "pos", ((F.length("poi_id") * 7 + F.col("t") + F.col("pos") * 3 + F.col("v")) % 25).cast("long").alias("region_id"))


@query(sql("SELECT traj_id, pos, region_id::BIGINT AS region_id FROM toy_votes", "toy_votes"))
def votes(spark, d):
    return _toy_votes(spark, d)


def _toy_boxes(spark, d):
    return _toy(spark, d).select(F.col("node").alias("region_id"), F.col("x").alias("south"), (F.col("x") + 0.5).alias("north"), F.col("y").alias("west"), (F.col("y") + 0.5).alias("east"))


@query(sql("SELECT traj_id, min(x) AS south, max(x) + 0.5 AS north, min(y) AS west, max(y) + 0.5 AS east FROM toy_votes JOIN toy ON node = region_id GROUP BY traj_id", "toy_votes", "toy"))
def mbr_box(spark, d):
    return rebuild.mbr(_toy_votes(spark, d), _toy_boxes(spark, d))


@query(sql("SELECT traj_id, count(*)::BIGINT AS n_regions FROM (SELECT traj_id, min(x) AS s, max(x) + 0.5 AS n, min(y) AS w, max(y) + 0.5 AS e FROM toy_votes JOIN toy ON node = region_id GROUP BY traj_id) JOIN toy ON x <= n AND x + 0.5 >= s AND y <= e AND y + 0.5 >= w GROUP BY traj_id", "toy_votes", "toy"))
def mbr_candidates(spark, d):
    return rebuild.candidates(mbr_box(spark, d), _toy_boxes(spark, d)).groupBy("traj_id").agg(F.count(F.lit(1)).alias("n_regions"))


@query(sql("SELECT * FROM toy_nodes", "toy_nodes"))
def node_error(spark, d):
    return rebuild.node_error(_toy_votes(spark, d), _toy_d(spark, d))


@query(sql("SELECT * FROM toy_bierr", "toy_bierr"))
def edge_error(spark, d):
    return rebuild.edge_error(node_error(spark, d), _toy_edges(spark, d))


@query(sql("""SELECT traj_id, cost FROM (WITH RECURSIVE walk AS (SELECT traj_id, pos, dst AS at, min(err) AS cost FROM toy_bierr WHERE pos = 1 GROUP BY ALL
    UNION ALL (SELECT e.traj_id, e.pos, e.dst, min(round(w.cost + e.err, 6)) FROM walk w JOIN toy_bierr e ON e.traj_id = w.traj_id AND e.pos = w.pos + 1 AND e.src = w.at GROUP BY ALL))
    SELECT traj_id, arg_max(cost, pos) AS cost FROM (SELECT traj_id, pos, min(cost) AS cost FROM walk GROUP BY ALL) GROUP BY traj_id)""", "toy_bierr"))
def best_path(spark, d):
    """The least path of every valid trajectory, all lengths: those of one length share a plan."""
    err = edge_error(spark, d)
    err = staged(err.withColumn("len", F.max("pos").over(W.partitionBy("traj_id")) + 1))
    out = None
    for length in range(2, 9):
        one = rebuild.best_path(err.where(F.col("len") == length).drop("len"), length).select("traj_id", "cost")
        out = one if out is None else out.unionByName(one)
    return out


@query(sql("SELECT traj_id, (n * (len - 1))::BIGINT AS vars, ((n + 1) * (len - 1))::BIGINT AS cons FROM (SELECT traj_id, count(DISTINCT region_id) AS n, max(pos) AS len FROM toy_votes GROUP BY 1)", "toy_votes"))
def program_size(spark, d):
    per = _toy_votes(spark, d).groupBy("traj_id").agg(F.countDistinct("region_id").alias("n"), F.max("pos").alias("len"))
    v, c = cost.program_size(F.col("n"), F.col("len"))
    return per.select("traj_id", v.alias("vars"), c.alias("cons"))


_TRY = uniform_sql("'7'", "traj_id", "pos::VARCHAR", "attempt::VARCHAR")
#: Attempts are made in rounds; only what is unsolved goes on. The last bound is the cap of all attempts.
_ROUNDS = ((1, 64), (65, 2048), (2049, CFG.gamma))


def _round_sql(n: int) -> str:
    lo, hi = _ROUNDS[n]
    left = "SELECT * FROM valid" + "".join(f" WHERE traj_id NOT IN (SELECT traj_id FROM r{m})" if m == 0 else f" AND traj_id NOT IN (SELECT traj_id FROM r{m})" for m in range(n))
    return f"""r{n} AS MATERIALIZED (SELECT traj_id, min(attempt)::INTEGER AS attempt FROM (SELECT traj_id, attempt, bool_and(coalesce(s > b, true)) AS ok FROM (SELECT traj_id, attempt, s, lag(s) OVER (PARTITION BY traj_id, attempt ORDER BY pos) AS b
        FROM (SELECT traj_id, pos, attempt, t // 36 * 36 + floor({_TRY} * 36)::INTEGER AS s FROM ({left}), (SELECT unnest(range({lo}, {hi + 1})) AS attempt))) GROUP BY ALL) WHERE ok GROUP BY traj_id)"""


@query(sql(f"""SELECT traj_id, pos, CASE WHEN smoothed THEN min(least(t1, 143) - pos) OVER (PARTITION BY traj_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) + pos ELSE s END::INTEGER AS t, attempt, smoothed
    FROM (WITH {", ".join(map(_round_sql, range(len(_ROUNDS))))}, solved AS ({" UNION ALL ".join(f"SELECT * FROM r{n}" for n in range(len(_ROUNDS)))})
        SELECT *, max(s - pos) OVER (PARTITION BY traj_id ORDER BY pos) + pos AS t1 FROM (SELECT traj_id, pos, attempt, smoothed, t // 36 * 36 + floor({_TRY} * 36)::INTEGER AS s
            FROM (SELECT v.*, coalesce(attempt, {CFG.gamma}) AS attempt, attempt IS NULL AS smoothed FROM valid v LEFT JOIN solved USING (traj_id))))""", "valid"))
def fill_reject_first(spark, d):
    """Seeded time fills in six-hour bins: the first attempt whose slots rise, up to gamma attempts; then smoothed times."""
    valid = _valid(spark, d).select("traj_id", "pos", "t")

    def slot(attempt):
        return (F.floor(F.col("t") / 36) * 36 + F.floor(uniform(SEED, F.col("traj_id"), F.col("pos").cast("string"), attempt.cast("string")) * 36)).cast("int")

    left, solved = valid, None
    for n, (lo, hi) in enumerate(_ROUNDS):
        tries = left.withColumn("attempt", F.explode(F.sequence(F.lit(lo), F.lit(hi)))).withColumn("s", slot(F.col("attempt")))
        rising = F.coalesce(F.col("s") > F.lag("s").over(W.partitionBy("traj_id", "attempt").orderBy("pos")), F.lit(True))
        good = tries.withColumn("ok", rising).groupBy("traj_id", "attempt").agg(F.min("ok").alias("ok")).where("ok")
        first = staged(good.groupBy("traj_id").agg(F.min("attempt").alias("attempt")))
        solved = first if solved is None else solved.unionByName(first)
        left = left if n == len(_ROUNDS) - 1 else staged(left.join(first, "traj_id", "left_anti"))
    filled = valid.join(solved, "traj_id", "left").withColumn("smoothed", F.col("attempt").isNull()).withColumn("attempt", F.coalesce("attempt", F.lit(CFG.gamma)))
    filled = filled.withColumn("t", slot(F.col("attempt"))).withColumn("poi_id", F.lit(None).cast("string"))
    late = rebuild.smooth_times(filled.where("smoothed").withColumn("need", F.when(F.col("pos") == 1, 0).otherwise(1)))
    late = late.select("traj_id", "pos", "t").join(filled.select("traj_id", "pos", "attempt", "smoothed"), ["traj_id", "pos"])
    return filled.where("NOT smoothed").select("traj_id", "pos", "t", "attempt", "smoothed").unionByName(late)


_NEED = f"""SELECT *, sum(need) OVER (PARTITION BY traj_id ORDER BY pos) AS cum FROM (SELECT traj_id, pos, poi_id, t, CASE WHEN b_lat IS NULL THEN 0 ELSE greatest(1, ceil(round({HAV('b_lat', 'b_lon', 'lat', 'lon')}, 6) / 8.0 * 60 / 10)) END::INTEGER AS need
    FROM (SELECT r.*, p.lat, p.lon, lag(lat) OVER w AS b_lat, lag(lon) OVER w AS b_lon FROM released r JOIN poi p USING (poi_id) WINDOW w AS (PARTITION BY traj_id ORDER BY pos)))"""


@query(sql(f"""SELECT traj_id, pos, poi_id, (min(least(t1, 143) - cum) OVER (PARTITION BY traj_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) + cum)::INTEGER AS t
    FROM (SELECT *, max(t - cum) OVER (PARTITION BY traj_id ORDER BY pos) + cum AS t1 FROM ({_NEED}))""", "released", "poi"))
def smooth_times(spark, d):
    return rebuild.smooth_times(rebuild.need_slots(_released(spark, d), S.event_poi(spark, d), CFG))


# ---------------------------------------------------------------- measures


def _released(spark, d):
    p = S.event_poi(spark, d).select("poi_id", "l2")
    q = p.select(F.col("poi_id").alias("cand"), "l2")
    j = _valid(spark, d).join(p, "poi_id").join(F.broadcast(q), "l2")
    best = j.groupBy("traj_id", "pos", "t").agg(F.min(F.struct(uniform(SEED, F.col("traj_id"), F.col("pos").cast("string"), F.col("cand")).alias("u"), "cand")).alias("m"))
    return best.select("traj_id", "pos", F.col("m.cand").alias("poi_id"), "t")


def _errors(spark, d):
    return metrics.point_errors(_valid(spark, d), _released(spark, d), S.event_poi(spark, d))


@query(sql("SELECT dim, round(avg(v), 6) AS ne FROM (UNPIVOT (SELECT avg(d_t) AS t, avg(d_c) AS c, avg(d_s) AS s, avg(sqrt(d_t*d_t + d_c*d_c + d_s*d_s)) AS \"all\" FROM errors GROUP BY traj_id) ON t, c, s, \"all\" INTO NAME dim VALUE v) GROUP BY dim", "errors"))
def ne_by_dim(spark, d):
    return metrics.ne(_errors(spark, d))


def _prq(dim: str, deltas: list[float]):
    text = sql(f"SELECT delta, round(100 * avg(share), 6) AS pr FROM (SELECT traj_id, delta, avg((round({dim}, 6) <= delta)::INT::DOUBLE) AS share FROM errors, (SELECT unnest([{', '.join(map(str, map(float, deltas)))}]::DOUBLE[]) AS delta) GROUP BY ALL) GROUP BY delta", "errors")
    return text, lambda spark, d: metrics.prq(_errors(spark, d), dim, deltas)


for _name, _dim, _deltas in (("prq_space", "d_s", [0.05, 0.5, 1, 2, 4]), ("prq_time", "d_t", [0.5, 1, 2, 4]), ("prq_category", "d_c", [0, 1, 2, 3.5, 5, 10])):
    ORACLES[_name], QUERIES[_name] = _prq(_dim, _deltas)

_ETA = {"poi": 1, "grid4": 2, "l1": 5}


def _hot(spark, d, g: str, released: bool = False):
    t = _released(spark, d) if released else S.event_traj(spark, d)
    return hotspots.find(hotspots.visitors(t, S.event_poi(spark, d), g), g, _ETA[g])


@query(sql("SELECT * FROM hot_poi_traj", "hot_poi_traj"))
def hotspots_poi(spark, d):
    return _hot(spark, d, "poi")


@query(sql("SELECT * FROM hot_grid4_traj", "hot_grid4_traj"))
def hotspots_grid(spark, d):
    return _hot(spark, d, "grid4")


@query(sql("SELECT * FROM hot_l1_traj", "hot_l1_traj"))
def hotspots_category(spark, d):
    return _hot(spark, d, "l1")


_PAIR = "SELECT o.granularity, o.entity, o.t_s, o.t_e, o.peak, min((abs(o.t_s - r.t_s) + abs(o.t_e - r.t_e), r.t_s, r.peak)) FILTER (r.t_s IS NOT NULL) AS m FROM {o} o LEFT JOIN {r} r ON r.entity = o.entity GROUP BY ALL"


@query(sql("SELECT granularity, round(avg(m[1]), 6) AS ahd, round(avg(abs(peak - m[3])), 6) AS acd, count(m)::BIGINT AS n_pairs, sum((m IS NULL)::INT)::BIGINT AS n_unmatched FROM ("
           + " UNION ALL ".join(_PAIR.format(o=f"hot_{g}_released", r=f"hot_{g}_traj") for g in ("poi", "grid4", "l1")) + ") GROUP BY granularity", *[f"hot_{g}_{s}" for g in ("poi", "grid4", "l1") for s in ("released", "traj")]))
def ahd_acd(spark, d):
    out = None
    for g in ("poi", "grid4", "l1"):
        one = hotspots.ahd_acd(_hot(spark, d, g), _hot(spark, d, g, True))
        out = one if out is None else out.unionByName(one)
    return out


@query(sql("SELECT \"from\", \"to\", count(*)::BIGINT AS n FROM (SELECT poi_id AS \"from\", lead(poi_id) OVER (PARTITION BY traj_id ORDER BY pos) AS \"to\" FROM released) WHERE \"to\" IS NOT NULL GROUP BY ALL ORDER BY n DESC, \"from\", \"to\" LIMIT 20", "released"))
def trip_chains_topk(spark, d):
    return ops.trip_chains(_released(spark, d), 20)


@query(sql("SELECT l1, next_l1, n, round(n / sum(n) OVER (PARTITION BY l1), 6) AS rate FROM (SELECT l1, next_l1, count(*)::BIGINT AS n FROM (SELECT l1, lead(l1) OVER (PARTITION BY traj_id ORDER BY pos) AS next_l1 FROM released JOIN poi USING (poi_id)) WHERE next_l1 IS NOT NULL GROUP BY ALL)", "released", "poi"))
def next_category_rate(spark, d):
    return ops.next_category(_released(spark, d), S.event_poi(spark, d))


@query(sql("SELECT poi_id, t AS slot, (n * (n - 1) // 2)::BIGINT AS pairs FROM (SELECT poi_id, t, count(DISTINCT traj_id) AS n FROM released GROUP BY ALL) WHERE n > 1", "released"))
def copresence(spark, d):
    return ops.copresence(_released(spark, d))


# ---------------------------------------------------------------- other tables and operators


@query(sql("SELECT * FROM shop", "shop"))
def shopping_trajectories(spark, d):
    return S.shopping_traj(spark, d)


_SHOPKM = HAV("b_lat", "b_lon", "lat", "lon")


@query(sql(f"""SELECT len, count(*)::BIGINT AS n FROM (SELECT traj_id, count(*)::INTEGER AS len, bool_and(b_t IS NULL OR online OR b_online OR {_SHOPKM} <= 900.0 * (t - b_t)) AS ok FROM (SELECT *, lag(lat) OVER w AS b_lat, lag(lon) OVER w AS b_lon, lag(online) OVER w AS b_online, lag(t) OVER w AS b_t
    FROM shop JOIN (SELECT s_suppkey AS store, -40.0 + 20 * n_regionkey + 2 * (n_nationkey // 5) AS lat, -150.0 + 12 * n_nationkey AS lon, s_suppkey % 5 = 0 AS online FROM supplier JOIN nation ON s_nationkey = n_nationkey) USING (store) WINDOW w AS (PARTITION BY traj_id ORDER BY pos)) GROUP BY traj_id) WHERE ok GROUP BY len""", "shop"))
def wk_shopping(spark, d):
    """Reachable purchase sequences by length: 900 km a day, online stores always reachable."""
    w = W.partitionBy("traj_id").orderBy("pos")
    j = S.shopping_traj(spark, d).join(F.broadcast(S.shopping_stores(spark, d)), "store")
    j = j.select("traj_id", "t", "online", "lat", "lon", F.lag("lat").over(w).alias("b_lat"), F.lag("lon").over(w).alias("b_lon"), F.lag("online").over(w).alias("b_online"), F.lag("t").over(w).alias("b_t"))
    ok = F.col("b_t").isNull() | F.col("online") | F.col("b_online") | (D.haversine_km(F.col("b_lat"), F.col("b_lon"), F.col("lat"), F.col("lon")) <= 900.0 * (F.col("t") - F.col("b_t")))
    per = j.groupBy("traj_id").agg(F.count(F.lit(1)).cast("int").alias("len"), F.min(ok).alias("ok")).where("ok")
    return per.groupBy("len").agg(F.count(F.lit(1)).alias("n"))


def _spend(kind: str):
    body = f"SELECT r_name AS region, n_name AS nation, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY {kind}"

    def run(spark, d):
        o, c = table(spark, d, "orders").select("o_custkey"), table(spark, d, "customer").select("c_custkey", "c_nationkey")
        n, r = F.broadcast(table(spark, d, "nation")), F.broadcast(table(spark, d, "region"))
        j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
        j = j.select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"))
        count = F.count(F.lit(1)).alias("n")
        if kind.startswith("ROLLUP"):
            return j.rollup("region", "nation").agg(count)
        if kind.startswith("CUBE"):
            return j.cube("region", "nation").agg(count)
        return j.groupingSets([[F.col("region")], [F.col("nation")]], "region", "nation").agg(count)

    return body, run


for _name, _kind in (("visits_rollup", "ROLLUP (r_name, n_name)"), ("visits_cube", "CUBE (r_name, n_name)"), ("visits_sets", "GROUPING SETS ((r_name), (n_name))")):
    ORACLES[_name], QUERIES[_name] = _spend(_kind)


@query(sql("SELECT event_id, lag(poi_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev_poi FROM visits", "visits"))
def asof_last_place(spark, d):
    return ops.last_before(S.visits(spark, d), "user_id", ["ts", "event_id"], "poi_id", "prev_poi").select("event_id", "prev_poi")


@query("SELECT lang, token, count(*)::BIGINT AS n FROM (SELECT lang, unnest(string_split(lower(text), ' ')) AS token FROM documents) WHERE token IN ('the', 'of', 'de', 'der', 'la') GROUP BY ALL")
def text_mentions(spark, d):
    return S.text_mentions(spark, d)


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS l2 FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 100 = 0")
def vector_dc_pairs(spark, d):
    """A search: the stated query set (ids divisible by 100) against all vectors."""
    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("b"), F.col("embedding").alias("eb"))
    asks = table(spark, d, "embeddings").where("vec_id % 100 = 0").select(F.col("vec_id").alias("a"), F.col("embedding").alias("ea"))
    return e.join(asks, F.col("a") != F.col("b")).select("a", "b", F.round(D.vector_l2(F.col("ea"), F.col("eb")), 6).alias("l2"))


@query(sql("SELECT c_mktsegment AS segment, count(*)::BIGINT AS people, round(sum(eps), 6) AS total FROM (SELECT c_mktsegment, CASE c_mktsegment WHEN 'BUILDING' THEN 1.0 WHEN 'MACHINERY' THEN 2.0 ELSE 5.0 END::DOUBLE AS eps FROM customer) GROUP BY 1"))
def wk_personal_eps(spark, d):
    c = table(spark, d, "customer").select("c_mktsegment", F.when(F.col("c_mktsegment") == "BUILDING", 1.0).when(F.col("c_mktsegment") == "MACHINERY", 2.0).otherwise(5.0).alias("eps"))
    return c.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("people"), F.round(F.sum("eps"), 6).alias("total"))


@query(sql("SELECT split_part(traj_id, '|', 1) AS person, count(DISTINCT traj_id)::BIGINT AS draws, 5.0::DOUBLE * count(DISTINCT traj_id) AS total FROM valid GROUP BY 1", "valid"))
def wk_multi_release(spark, d):
    """A person's k days spend k eps."""
    days = _valid(spark, d).select("traj_id").distinct().select(F.split("traj_id", r"\|")[0].alias("person"), F.lit(CFG.eps).alias("eps"))
    return budget.ledger(days, ["person"])
