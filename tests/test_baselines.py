"""Baselines against brute force, or by how well they find separated groups."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridhub import baselines as B
from gridhub.baselines import density, hierarchy, partition
from gridhub.baselines.common import Nearest
from gridhub.baselines.hierarchy import merge_tree
from gridhub.baselines.partition import Mixture
from gridhub.baselines.subspace import cover_boxes
from gridhub.operators.metrics import pair_scores, same_partition

AXES = ("x", "y")


@pytest.fixture(scope="module")
def blobs(spark):
    rng = np.random.default_rng(7)
    rows = [(h, float(h * 10 + a), float(h % 2 * 10 + b)) for h in range(4) for a, b in rng.normal(0, 0.4, (40, 2))]
    return spark.createDataFrame(rows, "hub int, x double, y double").cache()


RUNS = {
    "kmeans": lambda p: B.kmeans(p, AXES, 4), "minibatch": lambda p: B.minibatch_kmeans(p, AXES, 4), "gmm": lambda p: B.gaussian_mixture(p, AXES, 4),
    "mean_shift": lambda p: B.mean_shift(p, AXES, 3.0), "dbscan": lambda p: B.dbscan(p, AXES, 1.5, 4), "cells": lambda p: B.dbscan(p, AXES, 1.5, 4, "cells"),
    "ward": lambda p: B.ward(p, AXES, 4), "average": lambda p: B.linkage(p, AXES, 4), "single": lambda p: B.linkage(p, AXES, 4, "single"), "complete": lambda p: B.linkage(p, AXES, 4, "complete"),
    "single_parts": lambda p: B.single_linkage(p, AXES, 4, 0.5), "average_parts": lambda p: B.linkage_by_parts(p, AXES, 4, "average", 0.3), "complete_parts": lambda p: B.linkage_by_parts(p, AXES, 4, "complete", 0.3),
    "birch": lambda p: B.birch(p, AXES, 0.5, 10, 4), "spectral": lambda p: B.spectral(p, AXES, 4, 20), "affinity": lambda p: B.affinity_propagation(p, AXES, preference=-200.0),
}


@pytest.mark.parametrize("name", RUNS)
def test_separated_groups_are_found(blobs, name):
    found = RUNS[name](blobs)
    assert found.count() == 160
    assert pair_scores(found, "hub", "label").first().ari >= 0.97


def test_quadratic_methods_refuse(blobs):
    for run in (lambda: B.ward(blobs, AXES, 4, cap=100), lambda: B.spectral(blobs, AXES, 4, cap=100), lambda: B.affinity_propagation(blobs, AXES, cap=100)):
        with pytest.raises(B.BaselineTooLarge):
            run()


@pytest.mark.parametrize("link", ["average", "single", "complete"])
@pytest.mark.parametrize("k", [1, 17])
def test_linkage_by_parts_is_the_whole_tree(spark, link, k):
    rng = np.random.default_rng(k)
    x = np.concatenate([rng.uniform(0, 3, (40, 2)), rng.uniform(2, 9, (25, 2)), [[20.0, 20.0]] * 3])
    df = spark.createDataFrame([(float(a), float(b)) for a, b in x], "x double, y double")
    got = {(r.x, r.y): r.label for r in B.linkage_by_parts(df, AXES, k, link, 1.0).collect()}
    places = np.unique(x, axis=0)
    weight = np.array([(x == p).all(1).sum() for p in places])
    want = merge_tree(places, weight, k, link)
    assert len(set(got.values())) == len(set(want)) == min(k, len(places))
    assert len({(got[tuple(p)], w) for p, w in zip(places, want)}) == len(set(want))


def test_linkage_by_parts_on_ties_and_sizes(spark):
    line = spark.createDataFrame([(float(i), 0.0) for i in range(10)], "x double, y double")
    for k in (4, 10, 12):
        assert B.single_linkage(line, AXES, k, 0.5).agg(F.countDistinct("label")).first()[0] == min(k, 10)
    with pytest.raises(B.BaselineTooLarge):
        B.linkage_by_parts(line, AXES, 1, "average", 0.5, cap=5)


def test_ward_without_a_matrix(spark):
    rng = np.random.default_rng(2)
    x, w = rng.normal(0, 1, (300, 2)), rng.integers(1, 4, 300)
    one, other = hierarchy.merge_steps(x, w, "ward"), hierarchy.ward_steps(x, w)
    assert np.allclose([m[0] for m in one], [m[0] for m in other])
    for k in (2, 9, 50):
        a, b = (np.unique(hierarchy._unions(300, m[: 300 - k]), return_inverse=True)[1] for m in (one, other))
        assert len(set(zip(a, b))) == k


def test_mean_shift_places_every_point(spark):
    rng = np.random.default_rng(5)
    df = spark.createDataFrame([(float(v), 0.0) for v in 40 * rng.beta(1.2, 4, 3000)], "x double, y double")
    assert B.mean_shift(df, AXES, 1.0).where("label is null").count() == 0


def brute_dbscan(x, eps, min_pts):
    near = ((x[:, None] - x[None]) ** 2).sum(2) <= eps * eps
    core = near.sum(1) >= min_pts
    label = np.where(core, np.arange(len(x)), -1)
    for _ in range(len(x)):
        for i in np.flatnonzero(core):
            label[i] = label[np.flatnonzero(near[i] & core)].min()
    return core, near, label


@pytest.mark.parametrize("engine", ["blocks", "small blocks", "pairs", "cells"])
def test_dbscan_is_exact(spark, engine, monkeypatch):
    if engine == "small blocks":
        real = density._dbscan_blocks
        monkeypatch.setattr(density, "_dbscan_blocks", lambda at, axes, eps, m: real(at, axes, eps, m, side=3))
        engine = "blocks"
    rng = np.random.default_rng(3)
    x = np.round(rng.uniform(0, 10, (150, 2)), 3)
    core, near, label = brute_dbscan(x, 0.9, 5)
    df = spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(x)], "id int, x double, y double")
    got = {r.id: r.label for r in B.dbscan(df, AXES, 0.9, 5, engine).collect()}
    for i in np.flatnonzero(core):
        for j in np.flatnonzero(core):
            assert (got[i] == got[j]) == (label[i] == label[j])
    for i in np.flatnonzero(~core):
        beside = {got[j] for j in np.flatnonzero(near[i] & core)}
        assert got[i] in beside if beside else got[i] is None


def test_multi_density(spark, blobs):
    assert B.dbscan_multi(blobs, AXES, [0.3, 2.0], 4).count() == 160


def test_merge_tree_matches_plain_merging():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(25, 2))
    groups = [[i] for i in range(25)]
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    while len(groups) > 5:
        i, j = min(((i, j) for i in range(len(groups)) for j in range(i)), key=lambda p: d[np.ix_(groups[p[0]], groups[p[1]])].mean())
        groups[j] += groups.pop(i)
    got = merge_tree(x, np.ones(25), 5, "average")
    assert {frozenset(g) for g in groups} == {frozenset(np.flatnonzero(got == k)) for k in set(got)}


def test_grid_subspaces(spark, blobs):
    by_hash, by_scan = B.clique(blobs, AXES, 40, 0.01), B.clique(blobs, AXES, 40, 0.01, lookup="scan")
    assert same_partition(by_hash, by_scan)
    units = B.clique_units(blobs, AXES, 40, 0.01)
    dense = {(r.u0, r.u1) for r in units[(0, 1)].collect()}
    one = {r.u0 for r in units[(0,)].collect()}
    assert all(u in one for u, _ in dense) and (0,) in B.clique_units(blobs, AXES, 40, 0.01, mdl=True)
    boxes = cover_boxes(by_hash).collect()
    covered = {(x, y) for b in boxes for x in range(b.lo_tx, b.hi_tx + 1) for y in range(b.lo_ty, b.hi_ty + 1)}
    assert covered == {(r.tx, r.ty) for r in by_hash.collect()}
    with pytest.raises(B.BaselineTooLarge):
        B.clique(blobs, AXES, 40, 0.01, lookup="scan", scan_cap=1)
    assert by_hash.agg(F.sum("n")).first()[0] <= 160


def test_no_dense_unit_gives_no_rows(spark, blobs):
    assert B.full_units(blobs, AXES, 40, 0.9).collect() == []
    assert B.full_units(blobs, AXES, 40, 0.01).count() == B.clique_units(blobs, AXES, 40, 0.01)[(0, 1)].count() > 0


@pytest.mark.parametrize("engine", ["pairs", "cells"])
def test_close_pairs_are_thinned_not_written(spark, engine, monkeypatch):
    rows, real = [], density.stage
    monkeypatch.setattr(density, "stage", lambda df, name="t": (lambda out: rows.append(out.count()) or out)(real(df, name)))
    monkeypatch.setattr(density, "FOREST_EDGES", 50)
    at = np.random.default_rng(3).uniform(0, 1, (200, 2))
    df = spark.createDataFrame([(float(a), float(b)) for a, b in at], "x double, y double")
    assert B.dbscan(df, AXES, 0.5, 5, engine).agg(F.countDistinct("label"), F.count("label")).first()[:] == (1, 200)
    assert max(rows) <= 400  # 200 places have over 10,000 close pairs


def test_linkage_keeps_the_trees_of_parts_that_stay_apart(spark, monkeypatch):
    runs, real = [], hierarchy._dbscan_blocks
    monkeypatch.setattr(hierarchy, "_dbscan_blocks", lambda *a, **k: runs.append(a[2]) or real(*a, **k))
    rng = np.random.default_rng(9)
    x = np.concatenate([rng.uniform(0, 1, (30, 2)) + [50 * i, 0] for i in range(3)])
    df = spark.createDataFrame([(float(a), float(b)) for a, b in x], "x double, y double")
    got = {(r.x, r.y): r.label for r in B.linkage_by_parts(df, AXES, 3, "complete", 0.5).collect()}
    assert len({(got[tuple(p)], i // 30) for i, p in enumerate(x)}) == 3 and len(runs) == 1


@pytest.fixture(scope="module")
def many_groups(spark):
    rng = np.random.default_rng(4)
    rows = [(h, float(h % 20 * 10 + a), float(h // 20 * 10 + b)) for h in range(300) for a, b in rng.normal(0, 0.4, (12, 2))]
    return spark.createDataFrame(rows, "hub int, x double, y double").cache()


@pytest.mark.parametrize("dim", [1, 2, 3])
def test_nearest_centres_without_a_table_of_all_pairs(dim, monkeypatch):
    monkeypatch.setattr(Nearest, "TABLE", 1000)
    rng = np.random.default_rng(dim)
    centres, x = np.concatenate([rng.normal(0, 1, (200, dim)), rng.uniform(-50, 50, (100, dim))]), rng.uniform(-80, 80, (500, dim))
    all_pairs = ((x[:, None] - centres[None]) ** 2).sum(2)
    found, d2 = Nearest(centres).find(x)
    assert (found == all_pairs.argmin(1)).all() and np.allclose(d2, all_pairs.min(1))


def test_many_groups_of_kmeans_are_found_from_few_passes(many_groups, monkeypatch):
    passes, real = [], partition._moments
    monkeypatch.setattr(partition, "_moments", lambda rows, centres: passes.append(len(centres)) or real(rows, centres))
    assert pair_scores(B.kmeans(many_groups, AXES, 300), "hub", "label").first().ari >= 0.97
    assert len(passes) < 40 and max(passes) < 3600


def test_kmeans_computes_its_input_a_few_times_only(spark, many_groups):
    seen = spark.sparkContext.accumulator(0)

    def counted(batches):
        for pdf in batches:
            seen.add(len(pdf))
            yield pdf

    found = B.kmeans(many_groups.mapInPandas(counted, many_groups.schema), AXES, 300)
    assert found.count() == 3600 and seen.value <= 5 * 3600


@pytest.mark.parametrize("dim", [1, 2, 3])
def test_runs_of_points_find_the_nearest_of_all_centres(dim, monkeypatch):
    rng = np.random.default_rng(dim)
    centres = np.concatenate([rng.normal(0, 1, (200, dim)), rng.uniform(-50, 50, (300, dim)), rng.integers(-3, 3, (100, dim))])
    x = np.concatenate([rng.normal(0, 1, (3000, dim)), rng.integers(-3, 3, (900, dim)), rng.normal(9, 0.01, (999, dim)), rng.uniform(-400, 400, (60, dim))])
    x = x[np.lexsort((x[:, -1], np.floor(x[:, 0])))]
    all_pairs = ((x[:, None] - centres[None]) ** 2).sum(2)
    for few, chunk in ((128, 256), (3, 7)):
        monkeypatch.setattr(Nearest, "FEW", few)
        monkeypatch.setattr(Nearest, "CHUNK", chunk)
        for find in (Nearest(centres).along, Nearest(centres).find):
            found, d2 = find(x)
            assert (found == all_pairs.argmin(1)).all() and np.allclose(d2, all_pairs.min(1))


def test_runs_far_from_all_centres_meet_few_of_them(monkeypatch):
    rng = np.random.default_rng(3)
    near, met, single = Nearest(rng.uniform(0, 100, (20000, 2))), [], []
    facing, find = Nearest._facing, Nearest.find
    monkeypatch.setattr(Nearest, "_facing", lambda self, low, high: met.append(facing(self, low, high)) or met[-1])
    monkeypatch.setattr(Nearest, "find", lambda self, x: single.append(len(x)) or find(self, x))
    near.along(np.sort(rng.uniform(300, 310, (6400, 2)), 0))
    assert max(map(len, met)) < 200 and sum(single) < 640


def test_blocks_hold_every_point_once_and_neighbours_together(spark, monkeypatch):
    monkeypatch.setattr(partition, "BLOCK", 100)
    monkeypatch.setattr(partition, "FILE", 450)
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.uniform(0, 9, (1500, 2)), [[4.0, 4.0]] * 700, [[1e6, -1e6]]])
    rows = spark.createDataFrame([(float(a), float(b)) for a, b in x], "x double, y double").repartition(3)
    blocks = list(partition._unpacked(partition._blocks(partition._scan(rows, AXES)).toArrow().to_batches(), 2))
    held = np.concatenate(blocks)
    assert max(map(len, blocks)) <= 100 and (held[np.lexsort(held.T)] == x[np.lexsort(x.T)]).all()
    assert np.median([np.ptp(b, axis=0).prod() for b in blocks]) < 12


def test_minibatch_starts_hold_no_table_of_all_pairs(many_groups, monkeypatch):
    monkeypatch.setattr(Nearest, "TABLE", 1)
    assert pair_scores(B.minibatch_kmeans(many_groups, AXES, 300), "hub", "label").first().ari >= 0.97


@pytest.mark.parametrize("dim", [1, 2, 3])
def test_mixture_shares_are_those_of_all_gaussians(dim, monkeypatch):
    monkeypatch.setattr(Mixture, "TABLE", 500)
    rng, k = np.random.default_rng(dim), 40
    mean, turn = rng.uniform(-60, 60, (k, dim)), rng.normal(0, 1, (k, dim, dim)) * rng.choice([0.1, 1, 4], (k, 1, 1))
    cov, weight = turn @ turn.transpose(0, 2, 1) + 0.05 * np.eye(dim), rng.dirichlet(np.ones(k))
    x = np.concatenate([mean[rng.integers(0, k, 200)] + rng.normal(0, 1, (200, dim)), rng.uniform(-200, 200, (50, dim))])
    far = x[:, None] - mean[None]
    logs = np.log(weight) - 0.5 * np.linalg.slogdet(cov)[1] - 0.5 * np.einsum("nki,kij,nkj->nk", far, np.linalg.inv(cov), far)
    want = np.exp(logs - logs.max(1, keepdims=True))
    model, got = Mixture(weight, mean, cov), np.zeros(logs.shape)
    for at, c, share, _ in model.shares(x):
        got[at, c] = share
    assert np.allclose(got, want / want.sum(1, keepdims=True), atol=1e-9) and (model.best(x) == logs.argmax(1)).all()


def test_birch_takes_more_features_than_a_matrix_holds(spark):
    line = spark.range(7000).select((F.col("id") * 10).cast("double").alias("x"), F.lit(0.0).alias("y"))
    assert B.birch(line, AXES, 0.5, 50, 3500).agg(F.countDistinct("label"), F.count("label")).first()[:] == (3500, 7000)
