"""Shapes of clusters: the covariance ellipse in SQL, the least-area ellipse per group."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.config import Grid
from gridhub.operators.neighbors import tile_keys


def covariance_ellipse(clusters: DataFrame, sigmas: float = 2.0) -> DataFrame:
    """Count-weighted centre, half axes and angle of each cluster, in tile units.

    Moments are plain sums, so the whole is one grouped aggregate.
    """
    roots = [f"r_{k}" for k in tile_keys(clusters)]
    x, y, n = F.col("tx").cast("double"), F.col("ty").cast("double"), F.col("n").cast("double")
    m = clusters.groupBy(*roots).agg(F.sum(n).alias("w"), F.sum(n * x).alias("sx"), F.sum(n * y).alias("sy"), F.sum(n * x * x).alias("sxx"), F.sum(n * y * y).alias("syy"), F.sum(n * x * y).alias("sxy"))
    m = m.select(*roots, "w", (F.col("sx") / F.col("w")).alias("cx"), (F.col("sy") / F.col("w")).alias("cy"), "sxx", "syy", "sxy")
    m = m.withColumns({"vx": F.col("sxx") / F.col("w") - F.col("cx") * F.col("cx"), "vy": F.col("syy") / F.col("w") - F.col("cy") * F.col("cy"), "vxy": F.col("sxy") / F.col("w") - F.col("cx") * F.col("cy")})
    mean, spread = (F.col("vx") + F.col("vy")) / 2, F.sqrt(F.pow((F.col("vx") - F.col("vy")) / 2, 2) + F.pow("vxy", 2))
    return m.select(*roots, F.col("w").cast("bigint").alias("points"), "cx", "cy", (F.sqrt(F.greatest(mean + spread, F.lit(0.0))) * sigmas).alias("major"), (F.sqrt(F.greatest(mean - spread, F.lit(0.0))) * sigmas).alias("minor"), (F.atan2(2 * F.col("vxy"), F.col("vx") - F.col("vy")) / 2).alias("angle"))


def enclosing_ellipse(points: np.ndarray, tol: float = 1e-4, max_steps: int = 5000) -> tuple[np.ndarray, float, float, float]:
    """Centre, half axes and angle of the least-area ellipse around 2-d points.

    Weights on the points are moved towards the one that sticks out most, until none does
    by more than ``tol``.
    """
    pts = np.unique(np.asarray(points, float), axis=0)
    lift = np.column_stack([pts, np.ones(len(pts))]).T
    u = np.full(len(pts), 1 / len(pts))
    for _ in range(max_steps):
        m = np.einsum("ij,ji->i", lift.T @ np.linalg.pinv(lift * u @ lift.T), lift)
        j = int(m.argmax())
        excess = m[j] / 3 - 1
        if excess <= tol:
            break
        step = (m[j] - 3) / (3 * (m[j] - 1))
        u *= 1 - step
        u[j] += step
    centre = pts.T @ u
    cov = (pts - centre).T @ ((pts - centre) * u[:, None])
    values, vectors = np.linalg.eigh(cov)
    axes = np.sqrt(np.maximum(values, 0) * 2)
    return centre, float(axes[1]), float(axes[0]), float(np.arctan2(vectors[1, 1], vectors[0, 1]))


def least_ellipse(clusters: DataFrame, grid: Grid, of: str = "tiles", tol: float = 1e-4) -> DataFrame:
    """Least-area ellipse of each cluster's tile corners, or of its points, in axis units.

    Only row extremes can touch the ellipse, so each tile row (or point row) is reduced to
    its two ends before a group reaches a task.
    """
    roots = [f"r_{k}" for k in grid.keys]
    if of == "tiles":
        sx, sy = grid.scales
        rows = clusters.groupBy(*roots, "ty").agg(F.min("tx").alias("lo"), (F.max("tx") + 1).alias("hi"))
        ends = rows.select(*roots, F.explode(F.array(*[F.struct((F.col(x) / F.lit(sx)).cast("double").alias("x"), ((F.col("ty") + dy) / F.lit(sy)).cast("double").alias("y")) for x in ("lo", "hi") for dy in (0, 1)])).alias("p")).select(*roots, "p.x", "p.y")
    elif of == "points":
        ax, ay = grid.axes
        rows = clusters.groupBy(*roots, F.col(ay).cast("double").alias("y")).agg(F.min(F.col(ax).cast("double")).alias("lo"), F.max(F.col(ax).cast("double")).alias("hi"))
        ends = rows.select(*roots, F.explode(F.array("lo", "hi")).alias("x"), "y")
    else:
        raise ValueError("of is tiles or points")
    schema = ", ".join([f"{r} bigint" for r in roots] + [f"{c} double" for c in ("cx", "cy", "major", "minor", "angle")])

    def fit(key, pdf: pd.DataFrame) -> pd.DataFrame:
        centre, major, minor, angle = enclosing_ellipse(pdf[["x", "y"]].to_numpy(), tol)
        return pd.DataFrame([[*key, centre[0], centre[1], major, minor, angle]], columns=[*roots, "cx", "cy", "major", "minor", "angle"])

    return ends.distinct().groupBy(*roots).applyInPandas(fit, schema)
