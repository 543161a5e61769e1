"""Choices that Catalyst cannot make: engine, precision, number of partitions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

from gridhub.config import Grid, TileParams
from gridhub.operators.agglomerate import DRIVER_TILES, tile_clusters
from gridhub.operators.contract import tile_sketch


def engine_for(tiles: int) -> str:
    return "driver" if tiles <= DRIVER_TILES else "blocks"


def partitions_for(points: DataFrame, grid: Grid, tiles_per_partition: int = 5_000_000) -> int:
    """Shuffle partitions for the tile counts, from a HyperLogLog estimate."""
    return max(1, -(-int(tile_sketch(points, grid).first()["tiles"]) // tiles_per_partition))


def lowest_precision(sample: DataFrame, grids: list[Grid], good: Callable[[DataFrame], bool], params: TileParams | None = None) -> Grid | None:
    """The coarsest grid whose clusters of a sample satisfy ``good``; coarser is faster."""
    for grid in sorted(grids, key=lambda g: abs(g.scales[0])):
        if good(tile_clusters(sample, grid, params)):
            return grid
    return None
