"""Hubs, visits, network and measures on small rows with answers by hand or brute force."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridhub.config import Grid, TileParams
from gridhub.functions import geo, shape
from gridhub.operators import hubs as H
from gridhub.operators import metrics as M
from gridhub.operators.agglomerate import tile_clusters
from gridhub.sources.hubs import e7_grid, hub_grid, hub_points, replicas

GRID = Grid(("x", "y"), scale=1.0)


@pytest.fixture(scope="module")
def clusters(spark):
    rows = [(0, 0, 0, 0, 5), (0, 0, 1, 0, 7), (10, 0, 10, 0, 6), (20, 0, 20, 0, 6)]
    return spark.createDataFrame(rows, "r_tx bigint, r_ty bigint, tx bigint, ty bigint, n bigint")


def day(i, h=0):
    return dt.datetime(2024, 1, i, h)


@pytest.fixture(scope="module")
def trips(spark):
    rows = [(1, day(1), 0.5, 0.5), (1, day(1, 3), 1.5, 0.5), (1, day(2), 10.5, 0.5), (1, day(20), 10.5, 0.5), (1, day(21), 0.5, 0.5), (2, day(1), 20.5, 0.5), (2, day(2), 99.0, 99.0), (2, day(3), 20.5, 0.5)]
    return spark.createDataFrame(rows, "vehicle int, at timestamp, x double, y double")


def test_hub_rows(clusters):
    got = {r.r_tx: r for r in H.hubs(clusters, GRID).collect()}
    assert got[0].tiles == 2 and got[0].points == 12 and got[0].x == pytest.approx((5 * 0.5 + 7 * 1.5) / 12) and tuple(got[0].densest) == (1, 0)
    one = geo.degrees_to_metres
    assert got[0].area_m2 > got[10].area_m2 > 0 and one is not None
    assert H.filter_area(H.hubs(clusters, GRID), got[0].area_m2 * 0.9).count() == 1
    assert H.top_tiles(clusters, 1).where("r_tx = 0").first().n == 7


def test_near_hubs_are_found_and_merged(spark, clusters):
    hubs = H.hubs(clusters, GRID, 1e-3)
    pairs = H.near_hubs(hubs, 1100.0, 1e-3).collect()
    assert [(p.hub[0], p.other[0]) for p in sorted(pairs)] == [(0, 10)] or len(pairs) == 2
    merged = H.merge_near_hubs(clusters, H.near_hubs(hubs, 1200.0, 1e-3))
    assert merged.select("r_tx").distinct().count() == 1


def test_visits_network_usage(spark, trips, clusters):
    got = [(r.vehicle, r.visit, r.r_tx, r.rows) for r in H.visits(trips, clusters, GRID, "7 days").orderBy("vehicle", "visit").collect()]
    assert got == [(1, 1, 0, 2), (1, 2, 10, 1), (1, 3, 10, 1), (1, 4, 0, 1), (2, 1, 20, 2)]
    visits = H.visits(trips, clusters, GRID, "7 days")
    net = {(r.src[0], r.dst[0]): r.trips for r in H.hub_network(visits).collect()}
    assert net == {(0, 10): 1, (10, 0): 1}
    cube = H.usage_profile(visits, ("weekday",), "cube")
    assert cube.where("r_tx is null and r_ty is null and weekday is null").first().visits == 5
    assert H.usage_profile(visits, ("weekday",), "plain").agg(F.sum("visits")).first()[0] == 5
    assert H.usage_pivot(visits).count() == 3
    assert {(r.r_tx, r.vehicles) for r in H.hub_vehicles(trips, clusters, GRID, names=True).collect()} == {(0, 1), (10, 1), (20, 1)}


def test_as_of_and_interval(spark, trips, clusters):
    visits = H.visits(trips, clusters, GRID, "7 days")
    ev = spark.createDataFrame([(1, day(1, 1)), (1, day(5)), (1, dt.datetime(2023, 1, 1)), (2, day(2))], "vehicle int, at timestamp")
    asof = {(r.vehicle, r.at): r.visit for r in H.as_of_visit(ev, visits).collect()}
    assert asof == {(1, day(1, 1)): 1, (1, day(5)): 2, (1, dt.datetime(2023, 1, 1)): None, (2, day(2)): 1}
    assert sorted((r.vehicle, r.at) for r in H.events_in_visits(ev, visits).collect()) == [(1, day(1, 1)), (2, day(2))]


def brute_silhouette(x, labels, square):
    out = []
    for i in range(len(x)):
        d = ((x - x[i]) ** 2).sum(1)
        d = d if square else np.sqrt(d)
        mine = labels == labels[i]
        if mine.sum() == 1:
            out.append(0.0)
            continue
        a = d[mine].sum() / (mine.sum() - 1)
        b = min(d[labels == k].mean() for k in set(labels) - {labels[i]})
        out.append((b - a) / max(a, b))
    return float(np.mean(out))


def test_silhouettes_match_brute_force(spark):
    rng = np.random.default_rng(2)
    x = np.concatenate([rng.normal(c, 0.5, (12, 2)) for c in (0, 3, 9)] + [np.array([[30.0, 30.0]])])
    labels = np.array([0] * 12 + [1] * 12 + [2] * 12 + [3])
    df = spark.createDataFrame([(float(a), float(b), int(k)) for (a, b), k in zip(x, labels)] + [(1.0, 1.0, None)], "x double, y double, k int")
    assert M.silhouette(df, ("x", "y"), "k").first().silhouette == pytest.approx(brute_silhouette(x, labels, False), abs=1e-5)
    assert M.silhouette_fast(df, ("x", "y"), "k").first().silhouette == pytest.approx(brute_silhouette(x, labels, True), abs=1e-5)


@pytest.mark.parametrize("block", [4, 1024])
def test_silhouettes_of_uneven_clusters(spark, monkeypatch, block):
    rng = np.random.default_rng(6)
    ring = np.array([[12 * np.cos(t), 12 * np.sin(t)] for t in np.linspace(0, 6, 40)])
    x = np.concatenate([ring, rng.normal(0, 0.3, (15, 2)), rng.uniform(-20, 20, (60, 2)), rng.normal(6, 3, (30, 2)), np.repeat([[25.0, 0.0]], 5, 0)])
    labels = np.repeat([0, 1, 2, 3, 4], [40, 15, 60, 30, 5])
    df = spark.createDataFrame([(float(a), float(b), int(k)) for (a, b), k in zip(x, labels)], "x double, y double, k int")
    monkeypatch.setattr(M, "BLOCK", block)
    assert M.silhouette(df, ("x", "y"), "k").first().silhouette == pytest.approx(brute_silhouette(x, labels, False), abs=1e-5)
    assert M.silhouette_fast(df, ("x", "y"), "k").first().silhouette == pytest.approx(brute_silhouette(x, labels, True), abs=1e-5)


def test_scores(spark):
    df = spark.createDataFrame([(1, 5), (1, 5), (2, 6), (2, 6), (3, 6), (-1, None)], "hub int, label int")
    got = M.matched_ratio(df, "hub", ["label"]).first()
    assert (got.matched, got.hubs) == (1, 3)
    assert M.pair_scores(df.where("hub > 0"), "hub", "hub").first().ari == 1.0
    assert M.pair_scores(df.where("hub > 0"), "hub", "label").first().purity == 0.8


def test_overlap_and_equality(spark, clusters):
    assert M.same_partition(clusters, clusters) and not M.same_partition(clusters, clusters.where("tx > 0"))
    assert {r.jaccard for r in M.overlap(clusters, clusters).collect()} == {1.0}


def test_cost_measures(spark):
    assert M.speedup({1: 8.0, 2: 4.0, 4: 4.0})[4] == {"speedup": 2.0, "efficiency": 0.5}
    assert M.scaling_slope([10, 100, 1000], [1.0, 10.0, 100.0]) == pytest.approx(1.0)
    runs = spark.createDataFrame([(10, 1.0), (100, 10.0)], "size int, seconds double")
    assert M.scaling_slope_sql(runs).first().slope == pytest.approx(1.0)
    assert M.timed(lambda: spark.range(10), 2)["runs"] == 2 and M.ratio(4, 2) == 2
    def grow(n):
        if n > 10:
            raise MemoryError
        return spark.range(n)
    assert [r["ok"] for r in M.size_ladder(grow, [5, 10, 20, 40], 60)] == [True, True, False]
    assert set(M.phase_times([("a", lambda: spark.range(3))])) == {"a"}


@pytest.mark.parametrize("level, kept", [("3", 6), ("35", 10), ("4", 10), ("5", 0)])
def test_derived_hubs(spark, tiny, level, kept):
    found = tile_clusters(hub_points(spark, tiny), e7_grid(level), TileParams(5, 4))
    assert found.select("r_tx", "r_ty").distinct().count() == kept


def test_generators(spark):
    grid = hub_grid(spark, 9, 50)
    assert grid.count() == 450 and grid.select("hub").distinct().count() == 9
    found = tile_clusters(hub_grid(spark, 9, 500), e7_grid("35"), TileParams(5, 4))
    assert found.select("r_tx", "r_ty").distinct().count() == 9
    assert hub_grid(spark, 9, 50, layout="random").select("hub").distinct().count() <= 9
    assert replicas(grid, 3).count() == 1350


def test_cluster_shapes(spark, clusters):
    cov = shape.covariance_ellipse(clusters).where("r_tx = 0").first()
    assert cov.points == 12 and cov.minor == pytest.approx(0, abs=1e-9) and cov.major > 0
    least = shape.least_ellipse(clusters, GRID).where("r_tx = 10").first()
    assert (least.cx, least.cy) == (pytest.approx(10.5, abs=1e-3), pytest.approx(0.5, abs=1e-3)) and least.major == pytest.approx(2**-0.5, rel=1e-2)
