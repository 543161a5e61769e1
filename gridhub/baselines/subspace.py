"""Grid-based subspace clustering: dense units level by level, joined and covered."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.baselines.common import BaselineTooLarge
from gridhub.config import Neighborhood
from gridhub.operators.agglomerate import agglomerate
from gridhub.plans.staging import stage


def _units(points: DataFrame, axes: tuple[str, ...], xi: int) -> DataFrame:
    """Interval number of each axis, of ``xi`` equal ones between its ends."""
    ends = points.agg(*[F.min(a).cast("double").alias(f"lo{i}") for i, a in enumerate(axes)], *[F.max(a).cast("double").alias(f"hi{i}") for i, a in enumerate(axes)]).first()
    cut = {}
    for i, a in enumerate(axes):
        lo, hi = ends[f"lo{i}"], ends[f"hi{i}"]
        width = (hi - lo) / xi if lo is not None and hi > lo else 1.0
        cut[f"u{i}"] = F.least(F.floor((F.col(a).cast("double") - F.lit(lo)) / F.lit(width)), F.lit(xi - 1)).cast("bigint")
    return points.select(*[c.alias(n) for n, c in cut.items()])


def _minimal_description(rows: list[tuple[float, int]]) -> float:
    """Coverage below which subspaces are pruned: the split that codes both sides best."""
    import math

    cover = sorted((c for c, _ in rows), reverse=True)
    best, at = float("inf"), cover[-1] if cover else 0.0
    for i in range(1, len(cover)):
        cost = 0.0
        for part in (cover[:i], cover[i:]):
            mean = math.ceil(sum(part) / len(part))
            cost += math.log2(mean + 1) + sum(math.log2(abs(c - mean) + 1) for c in part)
        if cost < best:
            best, at = cost, cover[i - 1]
    return at


def clique_units(points: DataFrame, axes: tuple[str, ...], xi: int, density: float, mdl: bool = False) -> dict[tuple[int, ...], DataFrame]:
    """Dense units of every subspace that has any, bottom up.

    A unit of more axes can only be dense if all its faces are; a level therefore looks
    only at points inside dense units of the level below.  ``mdl`` also prunes subspaces
    that cover little.
    """
    units = stage(_units(points, axes, xi), "unit")
    need = density * units.count()
    level = {}
    for i in range(len(axes)):
        dense = stage(units.groupBy(f"u{i}").agg(F.count("*").alias("n")).where(F.col("n") >= need), "dense")
        if not dense.isEmpty():
            level[(i,)] = dense
    out = dict(level)
    while len(level) > 1:
        if mdl:
            cover = {s: d.agg(F.sum("n")).first()[0] or 0 for s, d in level.items()}
            least = _minimal_description([(c, 0) for c in cover.values()])
            level = {s: d for s, d in level.items() if cover[s] >= least}
        nxt = {}
        for a, b in combinations(sorted(level), 2):
            space = tuple(sorted(set(a) | set(b)))
            faces = [tuple(x for x in space if x != y) for y in space]
            if len(space) != len(a) + 1 or space in nxt or any(f not in level for f in faces):
                continue
            inside = units
            for face in faces:
                inside = inside.join(level[face].select(*[f"u{i}" for i in face]), [f"u{i}" for i in face], "left_semi")
            dense = stage(inside.groupBy(*[f"u{i}" for i in space]).agg(F.count("*").alias("n")).where(F.col("n") >= need), "dense")
            if not dense.isEmpty():
                nxt[space] = dense
        out |= nxt
        level = nxt
    return out


def full_units(points: DataFrame, axes: tuple[str, ...], xi: int, density: float) -> DataFrame:
    """``u0.., n``: dense units of the full space; no rows where none is dense."""
    full = tuple(range(len(axes)))
    found = clique_units(points, axes, xi, density).get(full)
    return points.sparkSession.createDataFrame([], ", ".join(f"u{i} bigint" for i in full) + ", n bigint") if found is None else found


def clique(points: DataFrame, axes: tuple[str, ...], xi: int, density: float, mdl: bool = False, lookup: str = "hash", scan_cap: int = 20_000) -> DataFrame:
    """Connected dense units of the full space: ``r_t*, t*, n``; faces touch, corners don't.

    ``lookup='scan'`` finds neighbours by comparing all pairs, to show what that costs.
    """
    found = clique_units(points, axes, xi, density, mdl)
    full = tuple(range(len(axes)))
    names = ("tx", "ty") if len(axes) == 2 else tuple(f"t{i}" for i in full)
    spark = points.sparkSession
    if full not in found:
        return spark.createDataFrame([], ", ".join([f"r_{k} bigint" for k in names] + [f"{k} bigint" for k in names]) + ", n bigint")
    sig = found[full].select(*[F.col(f"u{i}").alias(k) for i, k in enumerate(names)], "n")
    near = Neighborhood("manhattan", 1)
    if lookup == "hash":
        return agglomerate(sig, near)
    if lookup != "scan":
        raise ValueError("lookup is hash or scan")
    many = sig.count()
    if many > scan_cap:
        raise BaselineTooLarge("scanned lookup", many, scan_cap)
    from gridhub.operators.agglomerate import _named
    from gridhub.operators.components import star_components

    other = sig.select(*[F.col(k).alias(f"n_{k}") for k in names])
    steps = sum((F.abs(F.col(k) - F.col(f"n_{k}")) for k in names[1:]), F.abs(F.col(names[0]) - F.col(f"n_{names[0]}")))
    edges = sig.crossJoin(other).where(steps <= 1).select(F.struct(*names).alias("src"), F.struct(*[F.col(f"n_{k}").alias(k) for k in names]).alias("dst"))
    return _named(sig, star_components(edges))


def cover_boxes(clusters: DataFrame) -> DataFrame:
    """Few boxes that cover each cluster: greedy growth from the densest uncovered unit.

    One cluster is one group; its units, not its points, reach the task.
    """
    import numpy as np
    import pandas as pd

    keys = [c for c in clusters.columns if c.startswith("t")]
    roots = [f"r_{k}" for k in keys]
    schema = ", ".join([f"{r} bigint" for r in roots] + [f"lo_{k} bigint" for k in keys] + [f"hi_{k} bigint" for k in keys])

    def cover(key, pdf: pd.DataFrame) -> pd.DataFrame:
        cells = set(map(tuple, pdf[keys].to_numpy().tolist()))
        left, rows = set(cells), []
        while left:
            lo = list(min(left))
            hi = list(lo)
            for axis in range(len(keys)):
                for step, end in ((1, hi), (-1, lo)):
                    while True:
                        face = [range(a, b + 1) for a, b in zip(lo, hi)]
                        face[axis] = range(end[axis] + step, end[axis] + step + 1)
                        grid = np.array(np.meshgrid(*face)).reshape(len(keys), -1).T
                        if not all(tuple(c) in cells for c in grid.tolist()):
                            break
                        end[axis] += step
            left -= {c for c in left if all(a <= x <= b for a, x, b in zip(lo, c, hi))}
            rows.append([*key, *lo, *hi])
        return pd.DataFrame(rows, columns=[*roots, *[f"lo_{k}" for k in keys], *[f"hi_{k}" for k in keys]])

    return clusters.groupBy(*roots).applyInPandas(cover, schema)
