"""Points to tiles and back; cleaning and range predicates.  Catalyst expressions only."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridhub.config import Grid


def axis_tile(grid: Grid, i: int, column: Column | None = None) -> Column:
    """The tile number of one axis as BIGINT."""
    x = F.col(grid.axes[i]) if column is None else column
    if grid.project is not None:
        return grid.project(x).cast("bigint")
    if grid.offsets[i]:
        x = x + F.lit(Decimal(str(grid.offsets[i])) if grid.exact else grid.offsets[i])
    if grid.cell is not None:
        scaled = x / F.lit(float(grid.cell))
    elif grid.exact:
        scaled = x * F.lit(Decimal(repr(grid.scales[i])))
    else:
        scaled = x * F.lit(grid.scales[i])
    if grid.mode == "trunc":
        return F.when(scaled < 0, F.ceil(scaled)).otherwise(F.floor(scaled)).cast("bigint")
    return (F.floor(scaled) if grid.mode == "floor" else F.round(scaled)).cast("bigint")


def with_tile(points: DataFrame, grid: Grid) -> DataFrame:
    """Adds the tile columns.  A function of the coordinates: one tile for each point."""
    return points.withColumns({k: axis_tile(grid, i) for i, k in enumerate(grid.keys)})


def clean_points(points: DataFrame, grid: Grid, box: dict[str, tuple[float, float]] | None = None) -> DataFrame:
    """Rows whose axes are finite, inside ``box``, and whose tile numbers fit 63 bits."""
    keep = F.lit(True)
    for i, a in enumerate(grid.axes):
        x = F.col(a).cast("double")
        keep = keep & F.col(a).isNotNull() & ~F.isnan(x)
        limit = float("inf") if grid.project is not None else 2.0**62 / abs(grid.scales[i])
        keep = keep & (F.abs(x) < limit)
        if box and a in box:
            keep = keep & F.col(a).between(*box[a])
    return points.where(keep)


def dropped_rows(points: DataFrame, grid: Grid) -> DataFrame:
    """``rows, kept, dropped`` of ``clean_points`` in one pass."""
    ok = F.lit(True)
    for i, a in enumerate(grid.axes):
        x = F.col(a).cast("double")
        limit = float("inf") if grid.project is not None else 2.0**62 / abs(grid.scales[i])
        ok = ok & F.coalesce(~F.isnan(x) & (F.abs(x) < limit), F.lit(False))
    return points.agg(F.count("*").alias("rows"), F.count_if(ok).alias("kept"), F.count_if(~ok).alias("dropped"))


def tile_corner(tiles: DataFrame, grid: Grid) -> DataFrame:
    """Adds the least corner of each tile, named like the axes."""
    return tiles.withColumns({a: F.col(k) / F.lit(grid.scales[i]) - F.lit(grid.offsets[i]) for i, (a, k) in enumerate(zip(grid.axes, grid.keys))})


def tile_center(tiles: DataFrame, grid: Grid) -> DataFrame:
    shift = 0.0 if grid.mode == "round" else 0.5
    return tiles.withColumns({a: (F.col(k) + F.lit(shift)) / F.lit(grid.scales[i]) - F.lit(grid.offsets[i]) for i, (a, k) in enumerate(zip(grid.axes, grid.keys))})


def in_box(points: DataFrame, box: dict[str, tuple[float, float]]) -> DataFrame:
    """Plain range predicates, which reach the Parquet scan."""
    for a, (lo, hi) in box.items():
        points = points.where((F.col(a) >= lo) & (F.col(a) <= hi))
    return points


def tile_range(points: DataFrame, grid: Grid, low: tuple[int, ...], high: tuple[int, ...]) -> DataFrame:
    """Points of the tiles ``low..high``, written on the coordinates so that it is pushed down.

    ``floor(x * s) >= c`` is not pushed to the scan, ``x >= c / s`` is; the exact test on the
    tile follows for points that rounding puts on the edge.
    """
    if grid.mode != "floor" or grid.project is not None:
        raise ValueError("tile ranges are for floor grids")
    for i, (a, lo, hi) in enumerate(zip(grid.axes, low, high)):
        ends = sorted(((lo - 1e-6) / grid.scales[i] - grid.offsets[i], (hi + 1 + 1e-6) / grid.scales[i] - grid.offsets[i]))
        points = points.where((F.col(a) >= ends[0]) & (F.col(a) <= ends[1]))
    exact = with_tile(points, grid)
    for k, lo, hi in zip(grid.keys, low, high):
        exact = exact.where(F.col(k).between(lo, hi))
    return exact


def in_polygon(points: DataFrame, corners: list[tuple[float, float]], axes: tuple[str, str] = ("lon", "lat")) -> DataFrame:
    """Even-odd ray cast over the polygon's edges, as one codegen expression."""
    x, y = (F.col(a) for a in axes)
    crossings = F.lit(0)
    for (x1, y1), (x2, y2) in zip(corners, corners[1:] + corners[:1]):
        if y1 == y2:
            continue
        straddles = (F.lit(y1) > y) != (F.lit(y2) > y)
        crossings = crossings + (straddles & (x < (x2 - x1) * (y - y1) / (y2 - y1) + x1)).cast("int")
    return points.where(crossings % 2 == 1)


def vector_axes(vectors: DataFrame, column: str, dim: int) -> DataFrame:
    """The first ``dim`` components of an array column as columns ``v0, v1, ...``."""
    return vectors.withColumns({f"v{i}": F.get(F.col(column), F.lit(i)) for i in range(dim)})


def morton(tiles: DataFrame, bits: int = 21, name: str = "morton") -> DataFrame:
    """Interleaves two tile numbers, shifted to be non-negative, for locality in files."""
    half = 1 << (bits - 1)
    out = F.lit(0).cast("bigint")
    for i in range(bits):
        for j, k in enumerate(("tx", "ty")):
            bit = F.shiftright(F.col(k) + half, i).bitwiseAND(F.lit(1).cast("bigint"))
            out = out.bitwiseOR(F.shiftleft(bit, 2 * i + j))
    return tiles.withColumn(name, out)
