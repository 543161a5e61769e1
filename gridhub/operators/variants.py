"""Variants: keeping or labelling points, rescue of cut groups, relaxations, many grids."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridhub.config import Grid, Neighborhood, TileParams
from gridhub.operators.agglomerate import agglomerate, keep_clusters, tile_clusters
from gridhub.operators.components import star_components
from gridhub.operators.contract import count_distinct_points, count_tiles, significant
from gridhub.operators.neighbors import neighbours, tile_keys
from gridhub.operators.project import with_tile
from gridhub.plans.staging import stage

RETAIN = ("all", "distinct")


def label_points(points: DataFrame, clusters: DataFrame, grid: Grid) -> DataFrame:
    """Second pass: every point with the root of its tile's cluster, null for noise.

    A left join of the points to the small tile table; Spark broadcasts that table only
    while its measured size is below its own threshold.
    """
    keys = list(grid.keys)
    table = clusters.select(*keys, *[f"r_{k}" for k in keys])
    return with_tile(points, grid).join(table, keys, "left")


def retain_points(points: DataFrame, clusters: DataFrame, grid: Grid, retain: str = "all") -> DataFrame:
    """Points of clustered tiles with their cluster."""
    if retain not in RETAIN:
        raise ValueError(f"retain is one of {RETAIN}")
    if retain == "distinct":
        points = points.select(*grid.axes).distinct()
    keys = list(grid.keys)
    return with_tile(points, grid).join(clusters.select(*keys, *[f"r_{k}" for k in keys]), keys)


def tile_clusters_points(points: DataFrame, grid: Grid, params: TileParams | None = None, retain: str = "all", nested: bool = False, engine: str = "auto") -> DataFrame:
    """Clusters with their points.

    With ``retain='distinct'`` equal points count once, for the threshold as well.  Points
    stream through a join and are never held per tile, unless ``nested`` asks for one row
    per tile with its points in an array.
    """
    params = params or TileParams()
    counts = count_tiles(points, grid) if retain == "all" else count_distinct_points(points, grid)
    clusters = stage(keep_clusters(agglomerate(significant(counts, params.tau), params.near, engine), params.mu), "clusters")
    rows = retain_points(points, clusters, grid, retain)
    if not nested:
        return rows
    collect = F.collect_list if retain == "all" else F.collect_set
    return rows.groupBy(*[f"r_{k}" for k in grid.keys], *grid.keys).agg(F.array_sort(collect(F.struct(*grid.axes))).alias("points"))


def sliced_clusters_points(points: DataFrame, grid: Grid, params: TileParams | None = None, slices: int = 8, retain: str = "all", **how) -> DataFrame:
    """Sliced form that keeps its points."""
    from gridhub.operators.sliced import slice_clusters

    params = params or TileParams()
    counts = count_tiles(points, grid) if retain == "all" else count_distinct_points(points, grid)
    clusters = stage(slice_clusters(significant(counts, params.tau), params.near, slices, mu=params.mu, **how), "clusters")
    return retain_points(points, clusters, grid, retain)


def rescue_windows(counts: DataFrame, tau: int, scope: str = "all") -> DataFrame:
    """Significant tiles and those of 2^d windows that hold ``tau`` points together.

    ``all`` takes every such window; ``missed`` only windows without a significant tile,
    so a light tile beside a dense one is not drawn in.  Each tile adds its count to the
    2^d windows that hold it; no self-join.
    """
    keys = tile_keys(counts)
    corners = [tuple((i >> j) & 1 for j in range(len(keys))) for i in range(2 ** len(keys))]
    table = F.array(*[F.struct(*[F.lit(-x).cast("bigint").alias(f"d{i}") for i, x in enumerate(c)]) for c in corners])
    windows = counts.withColumn("_o", F.explode(table)).select(*[(F.col(k) + F.col(f"_o.d{i}")).alias(k) for i, k in enumerate(keys)], "n", (F.col("n") >= tau).alias("dense"))
    sums = windows.groupBy(*keys).agg(F.sum("n").alias("total"), F.max("dense").alias("dense"))
    if scope == "missed":
        sums = sums.where(~F.col("dense"))
    elif scope != "all":
        raise ValueError("scope is all or missed")
    back = F.array(*[F.struct(*[F.lit(x).cast("bigint").alias(f"d{i}") for i, x in enumerate(c)]) for c in corners])
    held = sums.where(F.col("total") >= tau).withColumn("_o", F.explode(back)).select(*[(F.col(k) + F.col(f"_o.d{i}")).alias(k) for i, k in enumerate(keys)])
    wanted = held.unionByName(counts.where(F.col("n") >= tau).select(*keys)).distinct()
    return counts.join(wanted, list(keys), "left_semi")


def relax(counts: DataFrame, tau: int, eps: int, min_neighbors: int = 2, near: Neighborhood | None = None) -> DataFrame:
    """Significant tiles, and tiles at most ``eps`` short of tau beside enough of them."""
    keys = tile_keys(counts)
    sure = significant(counts, tau)
    light = counts.where((F.col("n") < tau) & (F.col("n") >= tau - eps))
    beside = neighbours(sure.select(*keys), near or Neighborhood()).groupBy(*[F.col(f"n_{k}").alias(k) for k in keys]).agg(F.count("*").alias("_dense"))
    joined = light.join(beside.where(F.col("_dense") >= min_neighbors).drop("_dense"), list(keys), "left_semi")
    return sure.unionByName(joined)


def agglomerate_adaptive(sig: DataFrame, delta: Callable[[Column], Column], delta_max: int, metric: str = "chebyshev", rule: str = "max") -> DataFrame:
    """Clusters where each tile brings its own reach, a function of its count.

    Two tiles join if their distance is within the larger (``max``) or smaller (``min``)
    of both reaches, which are cut off at ``delta_max``.
    """
    keys = tile_keys(sig)
    sig = stage(sig, "sig")
    reach = F.least(delta(F.col("n")).cast("int"), F.lit(delta_max))
    own = sig.select(*keys, reach.alias("reach"))
    around = neighbours(own, Neighborhood(metric, delta_max), half=True)
    other = own.select(*[F.col(k).alias(f"n_{k}") for k in keys], F.col("reach").alias("n_reach"))
    steps = [F.abs(F.col(k) - F.col(f"n_{k}")) for k in keys]
    distance = (F.greatest(*steps) if len(steps) > 1 else steps[0]) if metric == "chebyshev" else sum(steps[1:], steps[0])
    bound = F.greatest("reach", "n_reach") if rule == "max" else F.least("reach", "n_reach")
    met = around.join(other, [f"n_{k}" for k in keys]).where(distance <= bound)
    edges = met.select(F.struct(*keys).alias("src"), F.struct(*[F.col(f"n_{k}").alias(k) for k in keys]).alias("dst"))
    from gridhub.operators.agglomerate import _named

    return _named(sig, star_components(edges))


def multi_precision(points: DataFrame, grids: dict[str, Grid], params: TileParams | None = None, engine: str = "auto") -> DataFrame:
    """Clusters at several precisions, ``level`` naming each.

    Grids over the same axes whose scales divide the finest one are rolled up from its
    counts, so the points are scanned once for all of them.
    """
    params = params or TileParams()
    finest = max(grids.values(), key=lambda g: abs(g.scales[0]))
    fine = stage(count_tiles(points, finest), "fine")
    out = None
    for level, grid in grids.items():
        ratio = finest.scales[0] / grid.scales[0]
        nested = grid.mode == finest.mode == "floor" and grid.offsets == finest.offsets and abs(ratio - round(ratio)) < 1e-9
        counts = roll_up(fine, round(ratio)) if nested else count_tiles(points, grid)
        found = keep_clusters(agglomerate(significant(counts, params.tau), params.near, engine), params.mu).withColumn("level", F.lit(level))
        out = found if out is None else out.unionByName(found)
    return out


def roll_up(counts: DataFrame, factor: int) -> DataFrame:
    """Counts on a grid coarser by a whole factor, without the points."""
    keys = tile_keys(counts)
    return counts.groupBy(*[F.floor(F.col(k) / factor).cast("bigint").alias(k) for k in keys]).agg(F.sum("n").cast("bigint").alias("n"))


def refine(points: DataFrame, grid: Grid, split_at: int, factor: int = 2, max_levels: int = 3) -> DataFrame:
    """Tiles over ``split_at`` points are split again: ``level, tile, n`` of all leaves."""
    keys, out, now = list(grid.keys), None, points
    for level in range(max_levels + 1):
        here = Grid(grid.axes, scale=tuple(s * factor**level for s in grid.scales), mode=grid.mode, offset=grid.offset)
        counts = stage(count_tiles(now, here), "refine")
        last = level == max_levels
        leaves = (counts if last else counts.where(F.col("n") <= split_at)).select(F.lit(level).alias("level"), *keys, "n")
        out = leaves if out is None else out.unionByName(leaves)
        if last:
            break
        heavy = counts.where(F.col("n") > split_at)
        now = with_tile(now.drop(*keys), here).join(heavy.select(*keys), keys, "left_semi").drop(*keys)
    return out


def coarsen(counts: DataFrame, tau: int, factor: int = 2) -> DataFrame:
    """Tiles below tau are summed in their parent tile: ``level`` 0 kept, 1 coarser."""
    keys = tile_keys(counts)
    dense = counts.where(F.col("n") >= tau).select(F.lit(0).alias("level"), *keys, "n")
    light = roll_up(counts.where(F.col("n") < tau), factor).where(F.col("n") >= tau).select(F.lit(1).alias("level"), *keys, "n")
    return dense.unionByName(light)


def shade(sig: DataFrame, levels: int = 5) -> DataFrame:
    """Density class 1..levels of each tile within its cluster, for drawing.

    Classes are equal steps between the least and the greatest count of the cluster.
    """
    roots = [f"r_{k}" for k in tile_keys(sig)]
    span = Window.partitionBy(*roots)
    low, high = F.min("n").over(span), F.max("n").over(span)
    step = F.when(high > low, F.floor((F.col("n") - low) * levels / (high - low))).otherwise(F.lit(0))
    return sig.withColumn("shade", (F.least(step, F.lit(levels - 1)) + 1).cast("int"))


def wrap_axis(tiles: DataFrame, period: int) -> DataFrame:
    """Edges across a closed first axis, such as the 180 degree meridian."""
    keys = tile_keys(tiles)
    first = keys[0]
    left, right = tiles.where(F.col(first) == F.lit(-(period // 2))), tiles.where(F.col(first) == F.lit(period - period // 2 - 1))
    moved = right.select((F.col(first) - period).alias(first), *keys[1:], F.struct(*keys).alias("src"))
    around = neighbours(moved, Neighborhood())
    other = left.select(*[F.col(k).alias(f"n_{k}") for k in keys], F.struct(*keys).alias("dst"))
    return around.join(other, [f"n_{k}" for k in keys]).select("src", "dst")


__all__ = ["agglomerate_adaptive", "coarsen", "label_points", "multi_precision", "refine", "relax", "rescue_windows", "retain_points", "roll_up", "shade", "sliced_clusters_points", "tile_clusters", "tile_clusters_points", "wrap_axis"]
