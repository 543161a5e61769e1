"""Worked examples and hand answers for projection, contraction and agglomeration."""

from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from gridhub.config import Grid, Neighborhood, TileParams, canvas_tiles, precision_metres, tau_relaxed
from gridhub.operators import agglomerate as agglomeration
from gridhub.operators import contract, project, sliced, variants
from gridhub.operators.agglomerate import agglomerate, cluster_ids, keep_clusters, nested_clusters, tile_clusters
from gridhub.operators.sliced import block_clusters, slice_clusters, sliced_clusters
from gridhub.plans import inspect

ENGINES = ("driver", "star", "propagate", "blocks", "recursive")


def tiles(spark, rows, n=9):
    return spark.createDataFrame([(x, y, n) for x, y in rows], "tx bigint, ty bigint, n bigint")


def groups(df):
    out = {}
    for r in df.collect():
        out.setdefault((r.r_tx, r.r_ty), set()).add((r.tx, r.ty))
    return out


def flood(cells, near):
    """Plain flood fill over a set of tiles: the definition, one tile at a time."""
    left, out = set(cells), {}
    while left:
        seen, todo = set(), [left.pop()]
        while todo:
            t = todo.pop()
            seen.add(t)
            for o in near.all_offsets(2):
                u = (t[0] + o[0], t[1] + o[1])
                if u in left:
                    left.discard(u)
                    todo.append(u)
        out[min(seen)] = seen
    return out


EXAMPLE = [("1.005", "1.000"), ("1.009", "1.002"), ("1.008", "1.006")]


@pytest.mark.parametrize("exact", [True, False])
def test_three_points_share_one_tile(spark, exact):
    kind = "decimal(4,3)" if exact else "double"
    rows = [(Decimal(a), Decimal(b)) if exact else (float(a), float(b)) for a, b in EXAMPLE]
    counts = contract.count_tiles(spark.createDataFrame(rows, f"lon {kind}, lat {kind}"), Grid(precision=2, exact=exact))
    assert [tuple(r) for r in counts.collect()] == [(100, 100, 3)]
    assert contract.significant(counts, 3).count() == 1 and contract.significant(counts, 4).count() == 0


def test_double_and_decimal_differ_on_an_edge(spark):
    one = spark.createDataFrame([(Decimal("0.29"), Decimal("0.29"))], "lon decimal(3,2), lat decimal(3,2)")
    assert contract.count_tiles(one, Grid(precision=2, exact=True)).first().tx == 29
    assert contract.count_tiles(one.select(F.col("lon").cast("double"), F.col("lat").cast("double")), Grid(precision=2)).first().tx == 28


def test_modes_below_zero(spark):
    one = spark.createDataFrame([(-0.5, -0.5)], "lon double, lat double")
    got = {m: contract.count_tiles(one, Grid(precision=0, mode=m)).first().tx for m in ("trunc", "floor")}
    assert got == {"trunc": 0, "floor": -1}


def test_parameters_are_checked():
    for bad in (lambda: Grid(scale=0.0), lambda: Grid(), lambda: Grid(precision=1, scale=2.0), lambda: TileParams(0, 1), lambda: Neighborhood("euclid"), lambda: Neighborhood(delta=0)):
        with pytest.raises(ValueError):
            bad()


def test_scalars():
    assert canvas_tiles(360, 180, 3)["both_axes"] == 360 * 180 * 10**6
    assert precision_metres(5) == pytest.approx(1.11, abs=0.01) and precision_metres(6) == pytest.approx(0.111, abs=0.001)
    assert tau_relaxed(5) == 2 and tau_relaxed(8, 3) == 1


def test_neighbour_counts():
    assert [len(Neighborhood("manhattan", 1).all_offsets(d)) for d in (2, 3)] == [4, 6]
    assert [len(Neighborhood("chebyshev", 1).all_offsets(d)) for d in (2, 3)] == [8, 26]
    assert len(Neighborhood("manhattan", 3).all_offsets(2)) == 2 * 3 * 4
    for n in (Neighborhood(), Neighborhood("manhattan", 2)):
        assert 2 * len(n.half_offsets(3)) == len(n.all_offsets(3))


def test_neighbourhoods_join_as_drawn(spark):
    diagonal, gap = tiles(spark, [(0, 0), (1, 1)]), tiles(spark, [(0, 0), (2, 0)])
    many = lambda df, near: len(groups(agglomerate(df, near, "driver")))
    assert many(diagonal, Neighborhood()) == 1 and many(diagonal, Neighborhood("manhattan", 1)) == 2 and many(diagonal, Neighborhood("manhattan", 2)) == 1
    assert many(gap, Neighborhood()) == 2 and many(gap, Neighborhood("chebyshev", 2)) == 1 and many(gap, Neighborhood(offsets=((2, 0),))) == 1


def test_smallest_cluster(spark):
    lab = agglomerate(tiles(spark, [(0, 0), (0, 1), (9, 9), (9, 8), (9, 7)]), engine="driver")
    assert set(groups(keep_clusters(lab, 3))) == {(9, 7)}


@pytest.mark.parametrize("engine", ENGINES)
def test_engines_give_the_flood_fill(spark, engine):
    rng, near = __import__("random").Random(4), Neighborhood()
    cells = {(rng.randrange(-12, 12), rng.randrange(-12, 12)) for _ in range(150)}
    assert groups(agglomerate(tiles(spark, cells), near, engine)) == flood(cells, near)


@pytest.mark.parametrize("near, small, slice_tiles", [(Neighborhood("manhattan", 2), True, 1_000_000), (Neighborhood("chebyshev", 3), True, 9), (Neighborhood("manhattan", 2), False, 1_000_000), (Neighborhood("chebyshev", 3), False, 12)])
def test_slices_give_the_flood_fill(spark, near, small, slice_tiles, monkeypatch):
    monkeypatch.setattr(sliced, "SLICE_TILES", slice_tiles)
    if not small:
        monkeypatch.setattr(agglomeration, "DRIVER_TILES", 0)
    rng = __import__("random").Random(5)
    cells = {(rng.randrange(0, 60), rng.randrange(0, 20)) for _ in range(130)}
    df = tiles(spark, cells)
    for how in ({"slices": 1}, {"slices": 4}, {"slices": 8, "slicing": "minmax", "join": "sweep"}, {"slices": 16, "join": "tree"}):
        assert groups(slice_clusters(df, near, **how)) == flood(cells, near), how
    assert groups(block_clusters(df, near, 7)) == flood(cells, near)


def test_group_that_crosses_borders_again_and_again(spark):
    u = [(0, 0), (1, 0), (2, 0), (3, 0), (0, 4), (1, 4), (2, 4), (3, 4), (3, 1), (3, 2), (3, 3)] + [(10, y) for y in range(3)]
    for n in (2, 4, 8):
        for join in ("graph", "sweep", "tree"):
            got = groups(slice_clusters(tiles(spark, u), Neighborhood(), n, "minmax", join, mu=4))
            assert got == {(0, 0): set(u[:11])}


def test_group_split_below_mu_on_both_sides_is_kept(spark):
    row = [(x, 0) for x in range(6)]
    assert groups(slice_clusters(tiles(spark, row), Neighborhood(), 2, "minmax", mu=6)) == {(0, 0): set(row)}


@pytest.mark.parametrize("engine", ["driver", "star"])
def test_long_chain_is_one_component(spark, engine):
    chain = spark.range(5000).select(F.col("id").alias("tx"), F.lit(0).cast("bigint").alias("ty"), F.lit(9).cast("bigint").alias("n"))
    assert agglomerate(chain, engine=engine).select("r_tx", "r_ty").distinct().count() == 1


def test_cube_in_three_dimensions(spark):
    cube = spark.createDataFrame([(x, y, z, 9) for x in range(3) for y in range(3) for z in range(3)], "t0 bigint, t1 bigint, t2 bigint, n bigint")
    for engine in ("driver", "star", "blocks"):
        got = agglomerate(cube, Neighborhood("manhattan", 1), engine)
        assert got.select("r_t0", "r_t1", "r_t2").distinct().collect() == [(0, 0, 0)] and got.count() == 27


@pytest.mark.parametrize("engine", ENGINES)
def test_empty_input(spark, engine):
    empty = spark.createDataFrame([], "lon double, lat double")
    got = tile_clusters(empty, Grid(precision=2), engine=engine)
    assert got.columns == ["r_tx", "r_ty", "tx", "ty", "n"] and got.count() == 0


def test_unclean_rows(spark):
    rows = [(1.0, 1.0), (None, 1.0), (float("nan"), 1.0), (float("inf"), 1.0), (1e300, 1.0)]
    df, grid = spark.createDataFrame(rows, "lon double, lat double"), Grid(precision=2)
    assert contract.count_tiles(project.clean_points(df, grid), grid).count() == 1
    assert tuple(project.dropped_rows(df, grid).first()) == (5, 1, 4)
    assert project.clean_points(df, grid, {"lon": (2.0, 3.0)}).count() == 0


def test_four_points_on_four_tiles(spark):
    counts = tiles(spark, [(0, 0), (0, 1), (1, 0), (1, 1)], 1)
    assert contract.significant(counts, 4).count() == 0
    assert variants.rescue_windows(counts, 4).count() == 4 and variants.rescue_windows(counts, 4, "missed").count() == 4
    beside = counts.withColumn("n", F.when(F.col("tx") + F.col("ty") == 0, 9).otherwise(1).cast("bigint"))
    assert variants.rescue_windows(beside, 4).count() == 4 and variants.rescue_windows(beside, 4, "missed").count() == 1


def test_retaining_counts_points_once_or_always(spark):
    same = spark.createDataFrame([(0.001 * (i % 2), 0.0) for i in range(6)], "lon double, lat double")
    grid, params = Grid(precision=2), TileParams(5, 1)
    assert variants.tile_clusters_points(same, grid, params, "all").count() == 6
    assert variants.tile_clusters_points(same, grid, params, "distinct").count() == 0
    nested = variants.tile_clusters_points(same, grid, params, "all", nested=True).collect()
    assert len(nested) == 1 and len(nested[0].points) == 6


def test_labels_and_retained_points_agree(spark):
    rng = __import__("random").Random(1)
    pts = spark.createDataFrame([(rng.gauss(0, 0.02), rng.gauss(0, 0.02)) for _ in range(500)] + [(5.0 + i, 1.0) for i in range(20)], "lon double, lat double")
    grid, params = Grid(precision=2), TileParams(5, 2)
    clusters = tile_clusters(pts, grid, params)
    labelled = variants.label_points(pts, clusters, grid)
    assert labelled.count() == 520
    assert labelled.where("r_tx is not null").count() == variants.retain_points(pts, clusters, grid).count() == clusters.agg(F.sum("n")).first()[0]
    assert sliced_clusters(pts, grid, params, 4).exceptAll(clusters).count() == 0
    assert variants.sliced_clusters_points(pts, grid, params, 4).count() == labelled.where("r_tx is not null").count()
    assert nested_clusters(clusters).agg(F.sum("points")).first()[0] == clusters.agg(F.sum("n")).first()[0]
    assert cluster_ids(clusters).agg(F.min("cluster_id")).first()[0] == 0


def test_chunks_in_any_order(spark):
    pts = spark.range(1000).select((F.col("id") % 37 / 100).alias("lon"), (F.col("id") % 11 / 100).alias("lat"))
    grid = Grid(precision=1)
    whole = sorted(map(tuple, contract.count_tiles(pts, grid).collect()))
    parts = [pts.where(F.floor(F.col("lon") * 100) % 3 == i) for i in (2, 0, 1)]
    assert sorted(map(tuple, contract.count_chunks(parts, grid).collect())) == whole
    assert sorted(map(tuple, contract.tree_merge([contract.count_tiles(p, grid) for p in parts], 2).collect())) == whole
    a, b = (contract.count_tiles(p, grid) for p in parts[:2])
    assert sorted(map(tuple, contract.merge_counts(a, b).collect())) == sorted(map(tuple, contract.merge_counts(b, a).collect()))


def test_count_store_adds_generations(spark, tmp_path):
    grid = Grid(precision=1)
    store = contract.CountStore(spark, f"file://{tmp_path}/store", grid)
    pts = spark.createDataFrame([(0.15, 0.15)] * 3, "lon double, lat double")
    assert store.read().count() == 0
    store.add(pts)
    store.add(pts)
    assert [tuple(r) for r in store.read().collect()] == [(1, 1, 6)] and store.generation() == 2


def test_relaxations(spark):
    counts = spark.createDataFrame([(0, 0, 9), (1, 0, 9), (0, 1, 3), (9, 9, 3)], "tx bigint, ty bigint, n bigint")
    assert {(r.tx, r.ty) for r in variants.relax(counts, 5, 2).collect()} == {(0, 0), (1, 0), (0, 1)}
    far = tiles(spark, [(0, 0), (2, 0)], 3)
    assert len(groups(variants.agglomerate_adaptive(far, lambda n: F.when(n < 5, 2).otherwise(1), 3))) == 1
    assert {(r.level, r.tx, r.n) for r in variants.coarsen(counts, 5).collect()} == {(0, 0, 9), (0, 1, 9)}
    assert variants.roll_up(counts, 2).where("tx = 0 and ty = 0").first().n == 21
    shaded = variants.shade(agglomerate(counts.where("n < 99"), engine="driver"), 3)
    assert {r.shade for r in shaded.collect()} <= {1, 2, 3}


def test_splitting_keeps_every_point(spark):
    pts = spark.range(2000).select((F.col("id") % 50 / 100).alias("lon"), (F.col("id") % 40 / 100).alias("lat"))
    leaves = variants.refine(pts, Grid(scale=1.0), 100, 2, 3)
    assert leaves.agg(F.sum("n")).first()[0] == 2000 and leaves.agg(F.max("level")).first()[0] >= 1


def test_closed_axis(spark):
    ring = tiles(spark, [(-180, 0), (179, 1), (0, 0)])
    assert variants.wrap_axis(ring, 360).count() == 1


def test_polygons_boxes_and_ranges(spark):
    pts = spark.createDataFrame([(0.5, 0.5), (1.5, 0.5), (0.5, 1.5)], "lon double, lat double")
    square = [(0.0, 0.0), (1.0, 0.0), (1.0, 1.0), (0.0, 1.0)]
    assert project.in_polygon(pts, square).count() == 1 and project.in_box(pts, {"lon": (0.0, 1.0)}).count() == 2
    grid = Grid(precision=0)
    assert project.tile_range(pts, grid, (0, 0), (0, 0)).count() == 1
    corner = project.tile_corner(contract.count_tiles(pts, grid), grid)
    assert sorted((r.lon, r.lat) for r in corner.collect()) == [(0.0, 0.0), (0.0, 1.0), (1.0, 0.0)]
    assert project.tile_center(contract.count_tiles(pts, grid), grid).agg(F.min("lon")).first()[0] == 0.5
    assert project.morton(contract.count_tiles(pts, grid)).select("morton").distinct().count() == 3


def test_plans(spark, tiny):
    pts = spark.read.parquet(f"{tiny}/events.parquet")
    grid = Grid(("user_id", "value"), scale=0.1)
    counts = contract.significant(contract.count_tiles(pts, grid), 5)
    assert not inspect.has_python(counts) and not inspect.has_pair_join(counts)
    assert inspect.exchanges(counts) == 1 and inspect.read_columns(counts) == [{"user_id", "value"}]
    ranged = project.tile_range(pts.select("user_id", "value"), grid, (0, 0), (3, 3))
    assert "GreaterThanOrEqual(value" in inspect.pushed_filters(ranged)[0]
    from gridhub.operators.neighbors import tile_edges

    assert not inspect.has_pair_join(tile_edges(counts, Neighborhood())) and not inspect.has_python(tile_edges(counts, Neighborhood()))
    assert not inspect.has_python(variants.rescue_windows(counts, 5))


def test_driver_engine_goes_on_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(agglomeration, "DRIVER_TILES", 20)
    rng, near = __import__("random").Random(6), Neighborhood()
    cells = {(rng.randrange(-12, 12), rng.randrange(-12, 12)) for _ in range(150)}
    assert groups(agglomerate(tiles(spark, cells), near, "driver")) == flood(cells, near)


def test_recursive_engine_is_not_ended_by_spark_s_row_limit(spark):
    near, cells = Neighborhood(), {(x, y) for x in range(9) for y in range(3)}
    spark.conf.set(agglomeration.RECURSION_ROWS, "20")
    try:
        assert groups(agglomerate(tiles(spark, cells), near, "recursive")) == flood(cells, near)
        assert spark.conf.get(agglomeration.RECURSION_ROWS) == "20"
    finally:
        spark.conf.unset(agglomeration.RECURSION_ROWS)
