"""Frozen parameters: the grid, the neighbourhood of a tile, and the thresholds."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import product

from pyspark.sql import Column
from pyspark.sql import functions as F

MODES = ("floor", "trunc", "round")


@dataclass(frozen=True)
class Grid:
    """How coordinates become tiles.

    One of ``precision`` (powers of ten, real values allowed), ``scale`` (a factor, or one
    per axis; any non-zero real) or ``cell`` (a divisor, for integer axes).  ``offset``
    shifts the grid in units of the coordinates.  ``exact`` tiles decimals without a
    double.  ``project`` replaces the whole rule by a function of the axis column.
    """

    axes: tuple[str, ...] = ("lon", "lat")
    precision: float | None = None
    scale: float | tuple[float, ...] | None = None
    cell: float | None = None
    mode: str = "floor"
    offset: float | tuple[float, ...] = 0.0
    exact: bool = False
    project: Callable[[Column], Column] | None = None

    def __post_init__(self) -> None:
        object.__setattr__(self, "axes", tuple(self.axes))
        given = [x is not None for x in (self.precision, self.scale, self.cell, self.project)]
        if sum(given) != 1:
            raise ValueError("give one of precision, scale, cell, project")
        if self.mode not in MODES:
            raise ValueError(f"mode is one of {MODES}")
        if not self.axes:
            raise ValueError("a grid needs an axis")
        if self.project is None and any(s == 0 or not math.isfinite(s) for s in self.scales):
            raise ValueError("a scale is a finite number other than zero")

    @property
    def dim(self) -> int:
        return len(self.axes)

    @property
    def keys(self) -> tuple[str, ...]:
        """Names of the tile columns."""
        return ("tx", "ty") if self.dim == 2 else tuple(f"t{i}" for i in range(self.dim))

    @property
    def scales(self) -> tuple[float, ...]:
        """Tiles per unit of each axis."""
        if self.project is not None:
            raise ValueError("a projected grid has no scale")
        if self.precision is not None:
            each: float | tuple[float, ...] = 10.0**self.precision
        elif self.cell is not None:
            each = 1.0 / self.cell if self.cell else 0.0
        else:
            each = self.scale
        return tuple(each) if isinstance(each, (tuple, list)) else (float(each),) * self.dim

    @property
    def offsets(self) -> tuple[float, ...]:
        return tuple(self.offset) if isinstance(self.offset, (tuple, list)) else (float(self.offset),) * self.dim


def chebyshev(v: tuple[int, ...]) -> int:
    return max(abs(x) for x in v)


def manhattan(v: tuple[int, ...]) -> int:
    return sum(abs(x) for x in v)


METRICS = {"chebyshev": chebyshev, "manhattan": manhattan}


@dataclass(frozen=True)
class Neighborhood:
    """Tiles that join: within ``delta`` by a metric, or a list of offsets made symmetric."""

    metric: str = "chebyshev"
    delta: int = 1
    offsets: tuple[tuple[int, ...], ...] | None = None

    def __post_init__(self) -> None:
        if self.metric not in METRICS or self.delta < 1:
            raise ValueError("metric is chebyshev or manhattan, delta at least 1")

    @property
    def reach(self) -> int:
        """Largest step along one axis."""
        return self.delta if self.offsets is None else max((abs(x) for o in self.offsets for x in o), default=1)

    def all_offsets(self, dim: int) -> list[tuple[int, ...]]:
        if self.offsets is not None:
            both = {tuple(o) for o in self.offsets} | {tuple(-x for x in o) for o in self.offsets}
            return sorted(o for o in both if any(o))
        span = range(-self.delta, self.delta + 1)
        return [o for o in product(span, repeat=dim) if any(o) and METRICS[self.metric](o) <= self.delta]

    def half_offsets(self, dim: int) -> list[tuple[int, ...]]:
        """One of each pair of opposite offsets: enough to meet every edge once."""
        return [o for o in self.all_offsets(dim) if o > (0,) * dim]


@dataclass(frozen=True)
class TileParams:
    """Thresholds: points per significant tile, tiles per kept cluster, neighbourhood."""

    tau: int = 5
    mu: int = 4
    near: Neighborhood = field(default_factory=Neighborhood)

    def __post_init__(self) -> None:
        if self.tau < 1 or self.mu < 1:
            raise ValueError("tau and mu are at least 1")


def canvas_tiles(a: float, b: float, precision: float) -> dict[str, float]:
    """Bound on the tiles of an a x b canvas.

    ``both_axes`` scales each axis by 10^p; ``one_axis`` is the smaller figure that scales
    their product once.
    """
    return {"both_axes": a * b * 10 ** (2 * precision), "one_axis": a * b * 10**precision}


def precision_metres(decimals: int) -> float:
    """Ground length of the last decimal place of a degree at the equator."""
    return 111_319.49 / 10**decimals


def tau_relaxed(tau: int, dim: int = 2) -> int:
    """The lowered threshold for a group cut by the grid into 2^dim tiles."""
    return math.ceil(tau / 2**dim)
