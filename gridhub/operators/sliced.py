"""The sliced form: clusters inside slices at once, then across their borders.

Every edge of the tile graph lies inside a slice or between border zones of two slices, so
local components joined along border edges are the components of the whole.  Groups that
touch no border are settled at once.  Blocks are slices cut along every axis.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gridhub.config import Grid, Neighborhood, TileParams
from gridhub.operators.agglomerate import _frame, _label_table, _result_schema, few_tiles, keep_clusters, large_enough, seems_small
from gridhub.operators.components import star_components
from gridhub.operators.contract import count_tiles, significant
from gridhub.operators.neighbors import neighbours, tile_keys
from gridhub.operators.unionfind import join_labels, tile_components
from gridhub.plans.staging import stage

SLICINGS = ("domain", "minmax", "balanced")
JOINS = ("graph", "sweep", "tree")
#: Border edges between groups that the two ordered joins take to the driver.
ORDERED_EDGES = 1_000_000
#: Tiles along one side of a block, and of a slice on average.
BLOCK_SIDE, SLICE_TILES = 512, 1_000_000


def slice_bounds(sig: DataFrame, slices: int, slicing: str, near: Neighborhood, domain: tuple[int, int] | None = None, by: str = "tiles") -> list[int]:
    """The first column of every slice but the first; slices are at least ``reach`` wide."""
    if slicing not in SLICINGS:
        raise ValueError(f"slicing is one of {SLICINGS}")
    first = tile_keys(sig)[0]
    if slicing == "domain":
        if domain is None:
            raise ValueError("domain slicing needs the first and last tile column")
        low, high = domain
    else:
        row = sig.agg(F.min(first), F.max(first)).first()
        if row[0] is None:
            return []
        low, high = row
    if slicing == "balanced":
        load = F.count("*") if by == "tiles" else F.sum("n")
        columns = sig.groupBy(first).agg(load.alias("load"))
        # one row per tile column; the running share decides the slice of a column
        total = columns.agg(F.sum("load")).first()[0]
        upto = F.sum("load").over(Window.orderBy(first).rowsBetween(Window.unboundedPreceding, 0))
        part = F.least(F.floor((upto - F.col("load")) * slices / F.lit(total)), F.lit(slices - 1))
        cuts = sorted(r["at"] for r in columns.withColumn("part", part).groupBy("part").agg(F.min(first).alias("at")).collect())[1:]
    else:
        cuts = [low + (high + 1 - low) * i // slices for i in range(1, slices)]
    return _wide_enough(cuts, low, high, near)


def _wide_enough(cuts: list[int], low: int, high: int, near: Neighborhood) -> list[int]:
    out: list[int] = []
    for c in cuts:
        if c - (out[-1] if out else low) >= near.reach and high + 1 - c >= near.reach:
            out.append(c)
    return out


def _slice_of(column: Column, cuts: list[int]) -> Column:
    """Slice number by a balanced tree of comparisons."""
    if not cuts:
        return F.lit(0)
    def pick(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(column < cuts[mid], pick(lo, mid)).otherwise(pick(mid + 1, hi))
    return pick(0, len(cuts))


def local_components(sig: DataFrame, cell: list[str], near: Neighborhood) -> DataFrame:
    """Components inside each group of tiles that share the ``cell`` columns."""
    keys = tile_keys(sig)
    return sig.groupBy(*cell).applyInArrow(lambda t: _label_table(t, keys, near), _result_schema(sig))


def _border_edges(local: DataFrame, border: Column, cell: list[str], near: Neighborhood) -> DataFrame:
    """Pairs of local roots that a border edge joins, with the cells they come from."""
    keys = tile_keys(local)
    roots = F.struct(*[F.col(f"r_{k}").alias(k) for k in keys])
    edge = local.where(border).select(*keys, *cell, roots.alias("root"))
    around = neighbours(edge, near, half=True).withColumnRenamed("root", "src").drop(*keys)
    around = around.select("src", *[F.col(c).alias(f"s_{c}") for c in cell], *[F.col(f"n_{k}").alias(k) for k in keys])
    met = around.join(edge.withColumnRenamed("root", "dst"), list(keys))
    apart = F.lit(False)
    for c in cell:
        apart = apart | (F.col(c) != F.col(f"s_{c}"))
    return met.where(apart).select("src", "dst", *[F.least(c, f"s_{c}").alias(f"{c}_low") for c in cell], *[F.greatest(c, f"s_{c}").alias(f"{c}_high") for c in cell]).distinct()


def _ordered_roots(edges: DataFrame, order: str, slices: int) -> DataFrame | None:
    """Both join orders over group edges: right to left, or halving the borders."""
    many = edges.count()
    if many > ORDERED_EDGES:
        raise ValueError(f"{many} border edges; ordered joins take {ORDERED_EDGES}, use join='graph'")
    by_border = defaultdict(list)
    for r in edges.select("src", "dst", "slice_low").collect():
        by_border[r["slice_low"]].append((tuple(r["src"]), tuple(r["dst"])))
    parent: dict[tuple, tuple] = {}

    def find(x: tuple) -> tuple:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    def close(border: int) -> None:
        for a, b in by_border.get(border, ()):
            a, b = find(a), find(b)
            if a != b:
                parent[max(a, b)] = min(a, b)

    if order == "sweep":
        for border in range(slices - 2, -1, -1):
            close(border)
    else:
        width = 1
        while width < slices:  # slices in runs of 2 * width become one
            for border in range(width - 1, slices - 1, 2 * width):
                close(border)
            width *= 2
    rows = [(x, find(x)) for x in list(parent)]
    if not rows:
        return None
    kind = edges.schema["src"].dataType.simpleString()
    return edges.sparkSession.createDataFrame(rows, f"node {kind}, root {kind}")


def _relabel(local: DataFrame, roots: DataFrame | None) -> DataFrame:
    if roots is None:
        return local
    keys = tile_keys(local)
    flat = roots.select(*[F.col(f"node.{k}").alias(f"r_{k}") for k in keys], *[F.col(f"root.{k}").alias(f"m_{k}") for k in keys])
    joined = local.join(flat, [f"r_{k}" for k in keys], "left")
    return joined.select(*[F.coalesce(f"m_{k}", f"r_{k}").alias(f"r_{k}") for k in keys], *[c for c in local.columns if not c.startswith("r_")])


def _small_slices(tiles: pa.Table, keys: tuple[str, ...], near: Neighborhood, cuts: list[int]) -> pa.Table:
    """The sliced form in one process: components of every slice, then of every border zone.

    Two labels of one border component are joined; what lies off the borders is untouched.
    """
    x = np.stack([tiles[k].to_numpy() for k in keys], 1)
    order = np.lexsort(x.T[::-1])
    x, label = x[order], np.arange(len(order))
    ends = [0, *np.searchsorted(x[:, 0], cuts).tolist(), len(x)]
    for a, b in zip(ends, ends[1:]):
        if b > a:
            label[a:b] = a + tile_components(x[a:b], near)
    for c in cuts:
        a, b = np.searchsorted(x[:, 0], [c - near.reach, c + near.reach])
        if b > a:
            label = join_labels(label, np.arange(a, b), a + tile_components(x[a:b], near))
    roots, out = x[label], tiles.take(pa.array(order))
    for i, k in reversed(list(enumerate(keys))):
        out = out.add_column(0, f"r_{k}", pa.array(roots[:, i], pa.int64()))
    return out


def _small_cuts(tiles: pa.Table, keys: tuple[str, ...], slices: int, slicing: str, near: Neighborhood, domain: tuple[int, int] | None, by: str) -> list[int]:
    """``slice_bounds`` of tiles at hand."""
    at, back = np.unique(tiles[keys[0]].to_numpy(), return_inverse=True)
    if not len(at) or slicing != "balanced":
        low, high = domain if slicing == "domain" else (int(at[0]), int(at[-1])) if len(at) else (0, 0)
        return _wide_enough([low + (high + 1 - low) * i // slices for i in range(1, slices)], low, high, near)
    load = np.bincount(back, None if by == "tiles" else tiles["n"].to_numpy().astype(float))
    part = np.minimum(((np.cumsum(load) - load) * slices / load.sum()).astype(np.int64), slices - 1)
    return _wide_enough(at[np.sort(np.unique(part, return_index=True)[1])[1:]].tolist(), int(at[0]), int(at[-1]), near)


def slice_clusters(sig: DataFrame, near: Neighborhood, slices: int | None = 8, slicing: str = "balanced", join: str = "graph", mu: int = 1, domain: tuple[int, int] | None = None, by: str = "tiles") -> DataFrame:
    """Clusters of ``mu`` tiles or more through vertical slices; rows as ``agglomerate``.

    Groups without a border tile are tested against ``mu`` before the join, the others
    after it.  Up to DRIVER_TILES tiles all slices are solved in one process.  A slice is
    one task, so beyond that there are at least as many slices as hold SLICE_TILES each on
    average; ``slices`` None asks for no more.
    """
    if join not in JOINS:
        raise ValueError(f"join is one of {JOINS}")
    if slicing not in SLICINGS:
        raise ValueError(f"slicing is one of {SLICINGS}")
    if slicing == "domain" and domain is None:
        raise ValueError("domain slicing needs the first and last tile column")
    keys = tile_keys(sig)
    sig = sig if join == "graph" and seems_small(sig) else stage(sig, "sig")
    tiles = few_tiles(sig) if join == "graph" else None
    if tiles is not None:
        cuts = _small_cuts(tiles, keys, slices or 1, slicing, near, domain, by)
        return _frame(sig, large_enough(_small_slices(tiles, keys, near, cuts), keys, mu))
    sig = stage(sig, "sig") if not hasattr(sig, "_staged_at") else sig
    slices = max(slices or 1, -(-sig.count() // SLICE_TILES))
    cuts = slice_bounds(sig, slices, slicing, near, domain, by)
    first = F.col(keys[0])
    number = _slice_of(first, cuts)
    local = local_components(sig.withColumn("slice", number), ["slice"], near)
    border = F.lit(False)
    for c in cuts:
        border = border | first.between(c - near.reach, c + near.reach - 1)
    local = stage(local.withColumn("edge", border), "local")
    roots = [f"r_{k}" for k in keys]
    groups = local.groupBy(*roots).agg(F.count("*").alias("size"), F.max("edge").alias("touches"))
    settled = groups.where(~F.col("touches") & (F.col("size") >= mu)).select(*roots)
    open_groups = groups.where("touches").select(*roots)
    done = local.join(settled, roots, "left_semi").drop("slice", "edge")
    crossing = local.join(open_groups, roots, "left_semi")
    edges = stage(_border_edges(crossing, F.col("edge"), ["slice"], near), "border")
    merged = _ordered_roots(edges, "sweep" if join == "graph" else join, len(cuts) + 1) if join != "graph" or edges.count() <= ORDERED_EDGES // 4 else star_components(edges)
    return done.unionByName(keep_clusters(_relabel(crossing.drop("slice", "edge"), merged), mu))


def block_clusters(sig: DataFrame, near: Neighborhood, side: int = BLOCK_SIDE) -> DataFrame:
    """As ``slice_clusters`` with square blocks, so no group outgrows ``side ** d`` tiles."""
    side = max(side, near.reach)
    keys = tile_keys(sig)
    cell = [f"b_{k}" for k in keys]
    blocked = stage(sig.withColumns({b: F.floor(F.col(k) / side).cast("bigint") for b, k in zip(cell, keys)}), "sig")
    local = stage(local_components(blocked, cell, near), "local")
    border = F.lit(False)
    for k in keys:
        place = F.pmod(F.col(k), F.lit(side))
        border = border | (place < near.reach) | (place >= side - near.reach)
    edges = stage(_border_edges(local, border, cell, near), "border")
    merged = None if edges.isEmpty() else star_components(edges)
    return _relabel(local.drop(*cell), merged)


def sliced_clusters(points: DataFrame, grid: Grid, params: TileParams | None = None, slices: int = 8, slicing: str = "balanced", join: str = "graph", domain: tuple[float, float] | None = None, by: str = "tiles") -> DataFrame:
    """Base method in sliced form.  ``domain`` is a range of the first axis' coordinate."""
    params = params or TileParams()
    sig = significant(count_tiles(points, grid), params.tau)
    ends = None
    if domain is not None:
        ends = tuple(int(x * grid.scales[0] // 1) for x in domain)
    return slice_clusters(sig, params.near, slices, slicing, join, params.mu, ends, by)
