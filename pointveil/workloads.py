"""The experiment workloads: methods, sweeps, ablations and generated populations, as registered queries.

They draw and rebuild through the kernels, so SQL has no twin for them; tests hold their parts against brute force.
Sweeps run every setting over whole trajectory sets of one scenario (no sampling).
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import permutations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .config import Cfg
from .functions import distance as D
from .functions.rng import uniform
from .operators import audit, catalog, cost, expmech, hotspots, metrics, ops, reach, regions, synth
from .operators.perturb import packed, unpacked
from .plans import knowledge, pipeline
from .plans.knowledge import Knowledge
from .queries import _toy_bigrams, _toy_pairs
from .sources import scenarios as S
from .sources.io import staged, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
REGION_METHODS, ALL_METHODS = ("hier",), ("hier", "flat", "geo_only", "indep_reach", "indep_free")
#: Comparison setting of the error table: a unit sensitivity, which is not private at eps (see README).
UNIT = Cfg(delta_mode="unit")
#: The setting that keeps eps, and the comparison setting; tables that report errors give both.
MODES = {"diameter": Cfg(), "unit": UNIT}


def workload(fn):
    QUERIES[fn.__name__] = fn
    return fn


# ---------------------------------------------------------------- scenarios


def event_city(spark: SparkSession, d: str, cfg: Cfg) -> tuple[DataFrame, DataFrame, Knowledge]:
    """(places, valid trajectories, knowledge) of the event city."""
    poi, packs, k = event_packs(spark, d, cfg)
    return poi, unpacked(packs), k


def event_packs(spark: SparkSession, d: str, cfg: Cfg) -> tuple[DataFrame, DataFrame, Knowledge]:
    """The same with one row per trajectory."""
    poi = staged(S.event_poi(spark, d))
    return poi, _event_days(spark, d, poi, cfg), knowledge.build(poi, cfg)


def _event_days(spark: SparkSession, d: str, poi: DataFrame, cfg: Cfg) -> DataFrame:
    return staged(pipeline.valid_packs(S.event_days(spark, d, _tasks(spark)), knowledge.places(poi, cfg), cfg))


def _tasks(spark: SparkSession) -> int:
    return pipeline.TASKS_PER_CORE * spark.sparkContext.defaultParallelism


def _packs(dealt: DataFrame, poi: DataFrame, cfg: Cfg) -> DataFrame:
    """The valid of trajectories that are dealt by id, one row each."""
    return staged(packed(reach.valid_only(dealt, poi, cfg), "poi_id", "t"))


def _people(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select((F.col("c_custkey") - 1).alias("person"))


def panel_city(spark: SparkSession, d: str, cfg: Cfg) -> tuple[DataFrame, DataFrame, Knowledge]:
    """The event city's places with one generated trajectory per customer."""
    poi, packs, k = panel_packs(spark, d, cfg)
    return poi, unpacked(packs), k


def panel_packs(spark: SparkSession, d: str, cfg: Cfg, city: tuple[DataFrame, Knowledge] | None = None) -> tuple[DataFrame, DataFrame, Knowledge]:
    """The same with one row per trajectory; ``city``: the event city's places and their knowledge, if built already."""
    poi = city[0] if city else staged(S.event_poi(spark, d))
    k = city[1] if city else knowledge.build(poi, cfg)
    number = {p: i for i, p in enumerate(k.poi_ids)}
    by_hour = np.zeros((len(number), 24))
    for r in S.popularity_by_hour(spark, d).collect():  # places x 24 rows of the checked catalog
        by_hour[number[r.poi_id], r.hour] = r.visits
    q = [i / 20 for i in range(21)]
    dwell = np.array(table(spark, d, "events").agg(F.percentile_approx("value", q).alias("q")).first().q)
    return poi, _packs(_long(synth.panel(_people(spark, d), k, by_hour + 1e-6, dwell, cfg)), poi, cfg), k


def _long(traj: DataFrame) -> DataFrame:
    """Trajectories of three points and more, dealt by id."""
    dealt = traj.repartition(_tasks(traj.sparkSession), "traj_id")
    return dealt.withColumn("n", F.count(F.lit(1)).over(W.partitionBy("traj_id"))).where("n >= 3").drop("n")


def campus(spark: SparkSession, d: str, cfg: Cfg) -> tuple[DataFrame, DataFrame, Knowledge]:
    """The campus with three planted crowds."""
    poi, packs, k = campus_packs(spark, d, cfg)
    return poi, unpacked(packs), k


def campus_packs(spark: SparkSession, d: str, cfg: Cfg) -> tuple[DataFrame, DataFrame, Knowledge]:
    """The same with one row per trajectory."""
    poi = staged(S.campus_poi(spark, d))
    k = knowledge.build(poi, cfg)
    cats = {r.poi_id: r.l1 for r in poi.select("poi_id", "l1").collect()}
    people = _people(spark, d)
    traj = synth.campus(people, k, [cats[p] for p in k.poi_ids], people.count(), cfg)
    return poi, _packs(_long(traj), poi, cfg), k


SCENARIOS = {"event_city": event_city, "panel_city": panel_city, "campus": campus}
PACKS = {"event_city": event_packs, "panel_city": panel_packs, "campus": campus_packs}


def released(method: str, traj: DataFrame, k: Knowledge, cfg: Cfg) -> pipeline.RunResult:
    """Run once and stage: a release is written down, never drawn again."""
    return pipeline.RunResult(staged(pipeline.run(method, traj, k, cfg).rows))


def _stack(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _sums(packs: DataFrame, releases: list[tuple], tell=metrics.ne_of_block, fields: str = metrics.NE_FIELDS, by: tuple[str, ...] = ()) -> DataFrame:
    """What is told of releases (method, knowledge, settings, tags), added up by release and ``by``: one job, written down."""
    told = pipeline.measured(packs, [r[:3] for r in releases], tell, fields)
    sums = [f.split()[0] for f in fields.split(", ") if f.split()[1] in ("long", "double") and f.split()[0] not in by]
    out = staged(told.groupBy("setting", *by).agg(*[F.sum(c).alias(c) for c in sums]))
    tags = [{"method": r[0], **r[3]} for r in releases]
    return out.select(*[F.array(*[F.lit(t[name]) for t in tags])[F.col("setting")].alias(name) for name in tags[0]], *by, *sums)


def _ne(packs: DataFrame, releases: list[tuple], timed: bool = False) -> DataFrame:
    """(dim, ne, method, tags) of releases (method, knowledge, settings, tags); ``timed`` adds mean kernel seconds."""
    sums = _sums(packs, releases)
    each = F.explode(F.array(*[F.struct(F.lit(d[2:]).alias("dim"), F.round(F.col(d) / F.col("n"), 6).alias("ne")) for d in ("d_t", "d_c", "d_s", "d_all")]))
    seconds = [(F.col("seconds") / F.col("n")).alias("seconds")] if timed else []
    return sums.select(each.alias("e"), "method", *seconds, *releases[0][3]).select("e.*", "method", *["seconds"] * timed, *releases[0][3])


# ---------------------------------------------------------------- methods


def _run(method: str):
    def fn(spark, d):
        _, traj, k = event_city(spark, d, Cfg())
        return pipeline.run(method, traj, k, Cfg()).released

    fn.__name__ = f"run_{method}"
    return workload(fn)


for _m in ALL_METHODS:
    _run(_m)


@workload
def run_global(spark, d):
    """The whole-trajectory mechanism by its exact chain, on hourly slots (states: places x slots)."""
    cfg = Cfg(gt_min=60)
    poi = staged(S.event_poi(spark, d))
    traj = staged(reach.valid_only(S.event_traj(spark, d, gt_min=60), poi, cfg))
    return pipeline.run("global", traj, knowledge.places(poi, cfg), cfg).released


@workload
def wk_em_variants(spark, d):
    """Mean distance of the full draw, the subsampled one and permute-and-flip on one toy output set."""
    pairs = staged(_toy_bigrams(spark, d))
    forms = {"em": expmech.draw_gumbel(pairs, ["input"], 4.0, 1.0, "7"), "flip": expmech.draw_flip(pairs, ["input"], 4.0, 1.0, "7"), "subsample": expmech.draw_subsample(pairs, ["input"], 4.0, 1.0, "7", 0.2), "flip_literal": expmech.draw_flip_literal(pairs, ["input"], 4.0, 1.0, "7").drop("trials")}
    return _stack([c.join(pairs, (c.input == pairs.input) & (c.chosen == pairs.cand)).agg(F.avg("dist").alias("mean_d")).select(F.lit(n).alias("form"), "mean_d") for n, c in forms.items()])


@workload
def wk_ratio_and_tail(spark, d):
    """Empirical eps, and the mass past the tail bound, on the toy space."""
    law = staged(expmech.law(_toy_pairs(spark, d), ["input"], 2.0, 5.656854249492381))
    bound = expmech.tail_bound(2.0, 5.656854249492381, 25, 1.0)
    mass = audit.tail_check(law, law, bound).agg(F.max("mass").alias("mass"))
    return audit.empirical_eps(law).join(mass).select("eps", "mass", F.lit(float(np.exp(-1.0))).alias("allowed"))


# ---------------------------------------------------------------- the tables


@workload
def wk_ne_table(spark, d):
    """(scenario, delta_mode, method, dim, ne) for five methods and three data sets; only 'diameter' keeps eps."""
    out = []
    for name, make in PACKS.items():
        speed = 4.0 if name == "campus" else 8.0
        _, packs, k = make(spark, d, Cfg(speed_kmh=speed))
        out.append(_ne(packs, [(m, k, cfg.but(speed_kmh=speed), {"scenario": name, "delta_mode": mode}) for m in ALL_METHODS for mode, cfg in MODES.items()]))
    return _stack(out)


@workload
def wk_gain(spark, d):
    """How far the full method is below its best rival on the event city, in both sensitivity modes."""
    _, packs, k = event_packs(spark, d, Cfg())
    table = _ne(packs, [(m, k, cfg, {"delta_mode": mode}) for m in ALL_METHODS for mode, cfg in MODES.items()])
    return _stack([metrics.gain(table.where(F.col("delta_mode") == mode)).withColumn("delta_mode", F.lit(mode)) for mode in MODES])


@workload
def wk_runtime_table(spark, d):
    """(scenario, method, perturb, rebuild, other, total): mean kernel seconds per trajectory, and the rebuild share."""
    parts = []
    for name in ("event_city", "panel_city"):
        _, traj, k = SCENARIOS[name](spark, d, Cfg())
        parts += [released(m, traj, k, Cfg()).timings.select(F.lit(name).alias("scenario"), F.lit(m).alias("method"), "perturb", "rebuild", "other", "total") for m in ALL_METHODS]
    return _stack(parts).withColumn("rebuild_share", F.col("rebuild") / F.col("total"))


@workload
def wk_hotspots(spark, d):
    """(scenario, method, granularity, ahd, acd, ...): hotspot agreement on three sets, thresholds scaled (unit mode)."""
    out = []
    for name in SCENARIOS:
        cfg = UNIT.but(speed_kmh=4.0 if name == "campus" else 8.0)
        poi, packs, k = PACKS[name](spark, d, cfg)
        scale = packs.count() / 8000
        real = hotspots.find_all(unpacked(packs), poi, scale)
        counts = _sums(packs, [(m, k, cfg, {}) for m in ALL_METHODS], hotspots.counts_of_block(poi, k.poi_ids), hotspots.COUNT_FIELDS, ("granularity", "entity", "slot"))
        out.append(hotspots.ahd_acd(real, hotspots.of_counts(counts, scale, ("method",)), ("method",)).withColumn("scenario", F.lit(name)))
    return _stack(out).select("granularity", "ahd", "acd", "n_pairs", "n_unmatched", "method", "scenario")


@workload
def wk_plant_events(spark, d):
    """Hotspots of the real campus set: the three planted crowds must be among the highest peaks."""
    poi, traj, _ = campus(spark, d, Cfg(speed_kmh=4.0))
    return hotspots.find(hotspots.visitors(traj, poi, "l1"), "l1", 0).orderBy(F.desc("peak"), "entity", "t_s").limit(20)


@workload
def wk_contact_events(spark, d):
    """Places and times where crowds meet in the released set, highest peaks first."""
    poi, traj, k = event_city(spark, d, UNIT)
    r = released("hier", traj, k, UNIT).released
    return hotspots.find(hotspots.visitors(r, poi, "poi"), "poi", 1).orderBy(F.desc("peak"), "entity", "t_s").limit(50)


@workload
def wk_trip_chains(spark, d):
    _, traj, k = event_city(spark, d, UNIT)
    return ops.trip_chains(released("hier", traj, k, UNIT).released)


@workload
def wk_next_category(spark, d):
    poi, traj, k = event_city(spark, d, UNIT)
    return ops.next_category(released("hier", traj, k, UNIT).released, poi)


@workload
def wk_copresence(spark, d):
    _, traj, k = event_city(spark, d, UNIT)
    return ops.copresence(released("hier", traj, k, UNIT).released)


# ---------------------------------------------------------------- sweeps


@workload
def wk_vary_len(spark, d):
    """Error and kernel seconds by trajectory length, for every method on two sets (unit mode)."""
    out = []
    poi, days, k = event_packs(spark, d, UNIT)
    for name, packs in (("event_city", days), ("panel_city", panel_packs(spark, d, UNIT, (poi, k))[1])):
        sums = _sums(packs, [(m, k, UNIT, {"scenario": name}) for m in ALL_METHODS], by=("len",))
        out.append(sums.select("scenario", "method", F.col("len").cast("long").alias("len"), F.round(F.col("d_all") / F.col("n"), 6).alias("ne"), (F.col("seconds") / F.col("n")).alias("seconds")))
    return _stack(out)


@workload
def wk_vary_eps(spark, d):
    """Error and kernel seconds by total budget, every method (at eps, the private mode)."""
    _, packs, k = event_packs(spark, d, Cfg())
    return _ne(packs, [(m, k, Cfg(eps=e), {"eps": float(e)}) for m in ALL_METHODS for e in (0.01, 0.1, 1, 5, 10, 50, 500)], True)


@workload
def wk_const_eps(spark, d):
    """A constant budget per draw instead of a constant total, every method."""
    _, packs, k = event_packs(spark, d, Cfg())
    return _ne(packs, [(m, k, Cfg(eps_mode="per_draw", eps_draw=e), {"eps_draw": float(e)}) for m in ALL_METHODS for e in (0.5, 1, 5)], True)


@workload
def wk_vary_speed(spark, d):
    """Error and kernel seconds by speed, every method (unit mode)."""
    out = []
    for name, cfg in [(str(s), UNIT.but(speed_kmh=float(s))) for s in (4, 8, 12, 16)] + [("inf", UNIT.but(theta="inf", speed_kmh=1e6))]:
        _, packs, k = event_packs(spark, d, cfg)
        out.append(_ne(packs, [(m, k, cfg, {"speed": name}) for m in ALL_METHODS], True))
    return _stack(out)


@workload
def wk_vary_n(spark, d):
    _, packs, k = campus_packs(spark, d, UNIT.but(speed_kmh=4.0))
    return _ne(packs, [(m, k, UNIT.but(speed_kmh=4.0, n=n), {"n_": n}) for m in ("hier", "flat", "geo_only") for n in (1, 2, 3)], True).withColumnRenamed("n_", "n")


@workload
def wk_vary_poi(spark, d):
    """The number of places: trajectories through the most popular ones only."""
    full = staged(S.event_poi(spark, d))
    out = []
    for n in (100, 250, 500):
        poi = staged(catalog.top_popular(full, n))
        pts = S.event_traj(spark, d, 1, 10**6).join(F.broadcast(poi.select("poi_id")), "poi_id", "left_semi")
        cfg = UNIT.but(n_poi=n, kappa=max(2, n // 50))
        packs = _packs(S.to_traj(pts, F.col("traj_id"), F.col("t"), [F.col("poi_id")], tasks=_tasks(spark)), poi, cfg)
        if packs.isEmpty():
            continue
        k = knowledge.build(poi, cfg)
        out.append(_ne(packs, [(m, k, cfg, {"n_poi": n}) for m in ("hier", "flat", "indep_free")]))
    return _stack(out)


@workload
def wk_preproc_cost(spark, d):
    """Seconds of public preprocessing, and graph sizes, by places and speed."""
    import time

    full, rows = staged(S.event_poi(spark, d)), []
    for n in (100, 250, 500):
        for speed in (4.0, 8.0, 16.0):
            start = time.perf_counter()
            cfg = Cfg(speed_kmh=speed, kappa=max(2, n // 50))
            k = knowledge.build(staged(catalog.top_popular(full, n)), cfg)
            rows.append((n, speed, len(k.D), int(k.A.sum()), time.perf_counter() - start))
    return spark.createDataFrame(rows, "n_poi int, speed double, regions int, bigrams long, seconds double")


@workload
def wk_prq(spark, d):
    """Preservation ranges in space, time and category for all methods."""
    _, packs, k = event_packs(spark, d, UNIT)
    deltas = {"d_s": [0.05, 0.5, 1, 2, 4], "d_t": [0.5, 1, 2, 4], "d_c": [0, 1, 2, 3.5, 5, 10]}
    sums = _sums(packs, [(m, k, UNIT, {}) for m in ALL_METHODS], metrics.prq_of_block(deltas), metrics.PRQ_FIELDS, ("dim", "delta"))
    return sums.select("method", "dim", "delta", F.round(100 * F.col("share") / F.col("n"), 6).alias("pr"))


# ---------------------------------------------------------------- ablations


@workload
def wk_merge_ablation(spark, d):
    """All merging orders by three thresholds of places and of popularity: regions, and error of the full method.

    ``order`` begins with "popularity" where visits are held against the threshold, and is that alone for the default order;
    ``kappa`` is then as many times a place's mean visits (a fixed number of visits would merge nothing in a larger table).
    """
    poi = staged(S.event_poi(spark, d))
    packs, read, out = _event_days(spark, d, poi, UNIT), knowledge.catalogued(poi, UNIT), []
    visits, places = poi.agg(F.sum("popularity"), F.count(F.lit(1))).first()
    for order in permutations(UNIT.merge_order):
        name, releases = "-".join(order), []
        popular = "popularity" if order == UNIT.merge_order else f"popularity-{name}"
        for n in (3, 5, 10):
            for weight, kappa, label in ((None, n, name), ("popularity", -(-n * visits // places), popular)):
                cfg = UNIT.but(kappa=kappa, merge_order=order)
                k = knowledge.build(poi, cfg, weight=weight, read=read)
                releases.append(("hier", k, cfg, {"kappa": kappa, "order": label, "regions": len(k.D)}))
        out.append(_ne(packs, releases))  # a job for each order, so that the driver holds six of the graphs, not all
    return _stack(out).orderBy("order", "kappa", "dim")


@workload
def wk_split_ablation(spark, d):
    """Grid cells, clusters and known units as the spatial split."""
    poi = staged(S.event_poi(spark, d))
    packs = _event_days(spark, d, poi, UNIT)
    unit = poi.select("poi_id", (F.floor((F.col("lat") - 40.70) * 50)).cast("int").alias("unit"))
    splits = {"grid": None, "clusters": regions.cluster_cells(poi, 16), "units": regions.admin_cells(poi, unit)}
    out = []
    for name, cells in splits.items():
        k = knowledge.build(poi, UNIT, cells if cells is None else staged(cells))
        out.append(("hier", k, UNIT, {"split": name, "regions": len(k.D)}))
    return _ne(packs, out)


@workload
def wk_overlap_ablation(spark, d):
    _, packs, k = event_packs(spark, d, UNIT)
    forms = {"overlapping": UNIT, "disjoint": UNIT.but(overlap=False), "single": UNIT.but(n=1)}
    return _ne(packs, [("hier", k, c, {"form": n}) for n, c in forms.items()])


@workload
def wk_mbr_ablation(spark, d):
    """With and without the bounding box: errors and seconds."""
    _, packs, k = event_packs(spark, d, UNIT)
    return _ne(packs, [("hier", k, UNIT.but(mbr=b), {"mbr": b}) for b in (True, False)])


@workload
def wk_fill_forms(spark, d):
    """Rejection against the exact chain fill: smoothing and feasibility."""
    poi, traj, k = event_city(spark, d, UNIT)
    out = []
    for form in ("reject", "chain"):
        r = released("hier", traj, k, UNIT.but(fill=form)).released
        s, f = metrics.smoothing_rate(r).first().rate, metrics.feasible_rate(r, poi, UNIT, hours=False).first().rate
        out.append((form, s, f))
    return spark.createDataFrame(out, "form string, smoothed double, feasible double")


@workload
def wk_program_size(spark, d):
    """Variables (as printed, and by definition) and constraints by length on the event city's graph."""
    _, _, k = event_city(spark, d, Cfg())
    r, e = len(k.D), int(k.A.sum())
    rows = [(n, r * (n - 1), cost.true_variables(e, n), (r + 1) * (n - 1)) for n in range(3, 9)]
    return spark.createDataFrame(rows, "len int, vars_printed long, vars_true long, constraints long")


# ---------------------------------------------------------------- data preparation and other domains


@workload
def wk_clean_trips(spark, d):
    """Raw points jittered around places, snapped to the nearest within 100 m, repeats dropped, thinned at random."""
    poi = staged(S.event_poi(spark, d).select("poi_id", "lat", "lon"))
    v = S.visits(spark, d).join(F.broadcast(poi), "poi_id")
    u = lambda tag: uniform("7", tag, F.col("event_id").cast("string"), kind="xx") - 0.5
    raw = v.select(F.col("event_id").alias("id"), "user_id", "ts", (F.col("lat") + 0.003 * u("y")).alias("lat"), (F.col("lon") + 0.003 * u("x")).alias("lon"))
    near = S.snap(raw.select("id", "lat", "lon"), poi)
    j = raw.join(near, "id").withColumn("day", F.to_date("ts"))
    w = W.partitionBy("user_id", "day").orderBy("ts", "id")
    one = j.withColumn("before", F.lag("poi_id").over(w)).where(F.col("before").isNull() | (F.col("before") != F.col("poi_id")))
    key = F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd"))
    from .functions.timeline import slot

    return S.to_traj(one, key, slot(F.col("ts")), [uniform("7", F.col("id").cast("string"))])


@workload
def wk_filter_valid(spark, d):
    """How many trajectories survive each filter."""
    poi, t = staged(S.event_poi(spark, d)), staged(S.event_traj(spark, d))
    n = lambda df: df.select("traj_id").distinct().count()
    rows = [("length", n(t))] + [(f"reach_{s}", n(reach.valid_only(t, poi, Cfg(speed_kmh=float(s)), False))) for s in (4, 8, 12, 16)] + [("open_8", n(reach.valid_only(t, poi, Cfg())))]
    return spark.createDataFrame(rows, "filter string, trajectories long")


@workload
def wk_gen_panel(spark, d):
    return panel_city(spark, d, Cfg())[1]


@workload
def wk_gen_campus(spark, d):
    return campus(spark, d, Cfg(speed_kmh=4.0))[1]


@workload
def wk_text_popularity(spark, d):
    """Popularity raised by mentions in comments: places are named by hashed tokens."""
    docs = table(spark, d, "documents").select(F.explode(F.split(F.lower("text"), " ")).alias("token"))
    slot = F.pmod(F.xxhash64("token"), F.lit(500))
    mentions = docs.groupBy(slot.alias("slot")).agg(F.count(F.lit(1)).alias("mentions"))
    poi = S.event_poi(spark, d).withColumn("slot", F.pmod(F.xxhash64("poi_id"), F.lit(500)))
    signal = poi.select("poi_id", "slot").join(F.broadcast(mentions), "slot").select("poi_id", "mentions")
    return catalog.weighted(poi.drop("slot"), signal, 0.01).select("poi_id", "popularity")


@workload
def wk_vector_distance(spark, d):
    """An embedding distance as the quality: draws over all vectors for the stated query set (ids divisible by 100)."""
    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("cand"), F.col("embedding").alias("eb"))
    fn, diameter = D.registered("vector_l2")
    asks = table(spark, d, "embeddings").where("vec_id % 100 = 0").select(F.col("vec_id").alias("input"), "embedding")
    pairs = e.join(F.broadcast(asks)).select("input", "cand", fn(F.col("embedding"), F.col("eb")).alias("dist"))
    return expmech.draw_gumbel(pairs, ["input"], 5.0, diameter, "7")


@workload
def wk_stream_share(spark, d):
    """Closed user-days released from a file stream (availableNow into files)."""
    import uuid

    from .sources.io import staged as stage
    from .streaming import share

    cfg = Cfg()
    _, _, k = event_city(spark, d, cfg)
    pts = S.visits(spark, d).select("user_id", F.col("ts").cast("timestamp").alias("ts"), "poi_id")
    end = spark.createDataFrame([(0, "none")], "user_id long, poi_id string").withColumn("ts", F.lit("2030-01-01 00:00:00").cast("timestamp"))
    source = stage(pts.orderBy("ts").coalesce(1)), stage(end.select("user_id", "ts", "poi_id"))
    name = uuid.uuid4().hex
    root = source[0].inputFiles()[0].rsplit("/", 2)[0]
    folders = "{" + ",".join(f.inputFiles()[0].rsplit("/", 2)[1] for f in source) + "}"
    stream = spark.readStream.schema(pts.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/{folders}")
    out = share.share_days(share.stamped(stream), k, cfg)
    sink = out.writeStream.format("parquet").option("path", f"{root}/{name}").option("checkpointLocation", f"{root}/{name}-state")
    sink.outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{root}/{name}")
