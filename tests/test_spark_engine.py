"""The engine's DataFrame operators on small fixtures, and twins of chosen queries in DuckDB."""

import itertools

import duckdb
import pytest
from pyspark.sql import functions as F

from pointveil import queries as Q
from pointveil.config import Cfg
from pointveil.functions import distance, sqlreg, timeline
from pointveil.operators import audit, catalog, hotspots, metrics, ops, perturb, rebuild
from pointveil.schemas import conform

SF = "/root/testdata/sf0.001"


def twin(name):
    con = duckdb.connect()
    for t in ("nation", "region", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con.sql(Q.ORACLES[name]).df()


@pytest.mark.parametrize("name", ["traj_feasible", "em_draw_gumbel", "ne_by_dim", "best_path", "fill_reject_first", "global_literal", "global_subsample", "global_flip", "global_tail", "smooth_times", "hotspots_grid", "prq_space", "shopping_trajectories", "chain_first_marginal"])
def test_query_equals_its_twin(spark, name):
    got, want = Q.QUERIES[name](spark, SF).toPandas(), twin(name)
    assert sorted(got.columns) == sorted(want.columns)
    rows = lambda df: sorted(map(repr, df[sorted(df.columns)].astype(object).itertuples(index=False, name=None)))
    assert rows(got) == rows(want)


def test_time_and_hours(spark):
    df = spark.createDataFrame([(23, 4, 26), (1, 4, 26), (2, 4, 26), (1, 20, 2), (3, 20, 2), (5, None, None)], "h int, o int, c int")
    got = [r.ok for r in df.select(timeline.is_open(F.col("h"), F.col("o"), F.col("c")).alias("ok")).collect()]
    assert got == [True, True, False, True, False, True]
    one = spark.range(1).select(distance.time_h(F.lit(14.5), F.lit(17.5)).alias("a"), distance.time_h(F.lit(1.0), F.lit(23.0)).alias("b"), distance.time_h(F.lit(1.0), F.lit(23.0), "circular").alias("c")).first()
    assert (one.a, one.b, one.c) == (3.0, 12.0, 2.0)


def test_windows_and_coverage(spark):
    rows = spark.createDataFrame([(f"t{n}", list(range(n))) for n in range(1, 8)], "traj_id string, seq array<long>")
    for n in (1, 2, 3):
        w = perturb.all_windows(rows, "seq", n)
        assert audit.coverage(w, n).count() == 0
        sizes = {r.traj_id: r["count"] for r in w.groupBy("traj_id").count().collect()}
        assert all(sizes[f"t{m}"] == m + min(n, m) - 1 for m in range(1, 8))
    audit.assert_row_local(perturb.all_windows(rows, "seq", 2))
    with pytest.raises(AssertionError):
        audit.assert_row_local(rows.groupBy("traj_id").count())


def test_path_and_programme_agree(spark):
    d = {(a, b): abs(a - b) * 1.5 for a in range(5) for b in range(5)}
    edges = [(a, b) for a, b in itertools.product(range(5), repeat=2) if (a + b) % 3]
    votes = spark.createDataFrame([("x", 1, 0), ("x", 2, 4), ("x", 2, 1), ("x", 3, 3), ("x", 4, 2)], "traj_id string, pos int, region_id long")
    dist = spark.createDataFrame([(a, b, v) for (a, b), v in d.items()], "src long, dst long, d double")
    e = spark.createDataFrame(edges, "src long, dst long")
    err = rebuild.edge_error(rebuild.node_error(votes, dist), e)
    best = rebuild.best_path(err, 4).first()
    node = {1: [0], 2: [4, 1], 3: [3], 4: [2]}
    cost = lambda i, r: sum(d[v, r] for v in node[i])
    options = {p: sum(cost(i + 1, p[i]) + cost(i + 2, p[i + 1]) for i in range(3)) for p in itertools.product(range(5), repeat=4) if all(s in set(edges) for s in zip(p, p[1:]))}
    assert best.cost == pytest.approx(min(options.values())) and options[tuple(best.path)] == pytest.approx(best.cost)
    chosen = {f"{i + 1}:{a}:{b}" for i, (a, b) in enumerate(zip(best.path, best.path[1:]))}
    sums = {}
    for r in rebuild.as_program(err).collect():
        if r.var in chosen:
            sums[r.family, r.row] = sums.get((r.family, r.row), 0) + r.coef
    assert all(v == 1 for (f, _), v in sums.items() if f == "layer") and all(v == 0 for (f, _), v in sums.items() if f == "continuity")
    assert sums["objective", "min"] == pytest.approx(best.cost)


def test_hotspots_and_their_distance(spark):
    counts = spark.createDataFrame([("a", 8, 30), ("a", 9, 50), ("a", 10, 3), ("a", 12, 25), ("b", 1, 21)], "entity string, slot int, n long")
    got = {(r.entity, r.t_s, r.t_e, r.peak) for r in hotspots.find(counts, "poi", 20).collect()}
    assert got == {("a", 8, 10, 50), ("a", 12, 13, 25), ("b", 1, 2, 21)}
    real = spark.createDataFrame([("poi", "a", 9, 10, 40)], "granularity string, entity string, t_s int, t_e int, peak long")
    out = spark.createDataFrame([("poi", "a", 8, 10, 50), ("poi", "c", 1, 2, 5)], "granularity string, entity string, t_s int, t_e int, peak long")
    r = hotspots.ahd_acd(real, out).first()
    assert (r.ahd, r.acd, r.n_pairs, r.n_unmatched) == (1.0, 10.0, 1, 1)
    assert hotspots.compare(real, out).count() == 3


def test_catalog_rejects_and_refreshes(spark):
    rows = [("p", 1.0, 2.0, "a", "a/0", "a/0/0", 0, 24, 5), ("q", float("nan"), 2.0, "a", "a/0", "a/0/0", 0, 24, 5), ("r", None, 2.0, "a", "a/0", "a/0/0", 0, 24, 5)]
    poi = spark.createDataFrame(rows, "poi_id string, lat double, lon double, l1 string, l2 string, l3 string, open_h int, close_h int, popularity long")
    good = catalog.build(poi)
    assert [r.poi_id for r in good.collect()] == ["p"]
    new, touched = catalog.apply_delta(good, good.withColumn("popularity", F.lit(9).cast("long")))
    assert new.first().popularity == 9 and touched.count() == 1
    with pytest.raises(ValueError):
        conform(good.drop("lat"), "poi_id string, lat double")
    over = spark.createDataFrame([("p", 6, 10)], "poi_id string, open_h int, close_h int")
    rule = spark.createDataFrame([("a", 0, 3)], "l1 string, open_h int, close_h int")
    assert catalog.with_hours(good, rule, over).first().close_h == 10


def test_asof_and_delta(spark):
    left = spark.createDataFrame([("u", 5, "x"), ("u", 1, "y"), ("v", 9, "z")], "k string, t int, tag string")
    right = spark.createDataFrame([("u", 2, 7), ("u", 5, 8)], "k string, t int, val int")
    assert {(r.tag, r.val) for r in ops.asof(left, right, "k", "t", "val").collect()} == {("x", 8), ("y", None), ("z", None)}
    a, b = spark.createDataFrame([(1, 2), (1, 3)], "src int, dst int"), spark.createDataFrame([(1, 3), (4, 5)], "src int, dst int")
    assert {(r.src, r.dst, r.side) for r in ops.set_delta(a, b).collect()} == {(1, 2, "old"), (4, 5, "new")}


def test_sql_surface(spark):
    sqlreg.register(spark)
    assert spark.sql("SELECT time_h(1D, 23D) AS h, is_open_at(1, 4, 26) AS o, stc_cell(40.76D, 40.7D, 0.1D, 4) AS c").first() == (12.0, True, 2)
    assert spark.sql("SELECT count(*) AS n FROM spans(4, 2)").first().n == 5


def test_errors_of_equal_sets_are_zero(spark):
    poi = spark.createDataFrame([("p", 40.7, -74.0, "a/0/0"), ("q", 40.8, -74.0, "b/0/0")], "poi_id string, lat double, lon double, l3 string")
    t = spark.createDataFrame([("t", 1, "p", 3), ("t", 2, "q", 90)], "traj_id string, pos int, poi_id string, t int")
    assert all(r.ne == 0 for r in metrics.ne(metrics.point_errors(t, t, poi)).collect())


def test_small_gap_edges_respect_speed(spark):
    poi = Q.S.event_poi(spark, SF)
    n = {s: Q.reach.valid_only(Q.S.event_traj(spark, SF), poi, Cfg(speed_kmh=float(s)), False).select("traj_id").distinct().count() for s in (4, 8)}
    assert n == {4: 96, 8: 122}


@pytest.mark.parametrize("name", ["time_slots", "dist_time_pairs", "search_space_size"])
def test_small_domains_are_read_from_events(spark, name):
    got, want = Q.QUERIES[name](spark, SF), twin(name)
    rows = lambda df: sorted(map(tuple, df[sorted(df.columns)].itertuples(index=False, name=None)))
    assert any(f.endswith("/events.parquet") for f in got.inputFiles())
    assert rows(got.toPandas()) == rows(want) and len(want)


def test_search_space_of_columns(spark):
    from pointveil.operators import cost

    df = spark.createDataFrame([(1000, n) for n in range(3, 9)], "p int, n int").select("n", cost.log10_space(F.col("p"), F.col("n"), 15, 0.2).alias("v"))
    assert all(r.v == pytest.approx(cost.log10_search_space(1000, r.n, 15, 0.2), abs=1e-9) for r in df.collect())
