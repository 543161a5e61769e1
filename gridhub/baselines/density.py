"""Density methods on grids of cells: DBSCAN, its multi-density form, mean shift."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.baselines.common import back, close_pairs, number_roots, places, xs
from gridhub.operators.components import star_components
from gridhub.operators.unionfind import join_labels, label_components
from gridhub.plans.staging import stage

#: Edges that a task holds before it keeps only a forest of them.
FOREST_EDGES = 4_000_000


def _numbered(at: DataFrame, axes: tuple[str, ...]) -> DataFrame:
    """Places with an ``id`` that rises in the order of their coordinates."""
    return stage(at.orderBy(*xs(axes)).withColumn("id", F.monotonically_increasing_id()), "place")


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges ``src, dst, block`` that join what the task's edges join, at most one a node.

    Edges are thinned whenever FOREST_EDGES have come and are never all held.
    """
    held: list[tuple[np.ndarray, ...]] = []
    size = kept = 0

    def thin() -> tuple[np.ndarray, ...]:
        a, b, block = (np.concatenate(side) for side in zip(*held))
        nodes, first, at = np.unique(np.r_[a, b], return_index=True, return_inverse=True)
        label = label_components(len(nodes), at[: len(a)], at[len(a) :])
        under = np.flatnonzero(label != np.arange(len(nodes)))
        return nodes[label[under]], nodes[under], block[first[under] % len(a)]

    def batch() -> pa.RecordBatch:
        return pa.RecordBatch.from_pydict({c: pa.array(v) for c, v in zip(("src", "dst", "block"), held[0])})

    for b in batches:
        held.append(tuple(column.to_numpy() for column in b.columns))
        size += b.num_rows
        if size > kept + FOREST_EDGES:
            held = [thin()]
            size = kept = len(held[0][0])
            if kept > FOREST_EDGES:
                yield batch()
                held, size, kept = [], 0, 0
    if size:
        held = [thin()]
        yield batch()


def _from_cores(cores: DataFrame, others: DataFrame, axes: tuple[str, ...], eps: float) -> DataFrame:
    """Labels of places, from cores ``id, x.., node`` and the places that are none.

    Cores of one node are known to belong together.  Pairs are thinned where they are
    found: first in the task that joins them, then block by block.
    """
    width, edge = 128 * eps, "src long, dst long, block long"
    block = F.xxhash64(*[F.floor(F.col(x) / width) for x in xs(axes)])
    near = close_pairs(cores, axes, eps, ("id", "node")).where((F.col("id") < F.col("y_id")) & (F.col("node") != F.col("y_node")))
    thinned = near.select(F.col("node").alias("src"), F.col("y_node").alias("dst"), block.alias("block")).mapInArrow(_forest, edge)
    roots = star_components(thinned.repartition("block").mapInArrow(_forest, edge))
    rooted = stage(cores.join(roots, "node", "left").select(*xs(axes), F.coalesce("root", "node").alias("root")), "core")
    # a border place joins the cluster of its least root among the cores within eps
    borders = close_pairs(others, axes, eps, ("root",), rooted).groupBy(*xs(axes)).agg(F.min("y_root").alias("root"))
    return number_roots(rooted.unionByName(borders), F.col("root"), axes)


def _dbscan_places(at: DataFrame, axes: tuple[str, ...], eps: float, min_pts: int) -> DataFrame:
    """All close pairs, counted as they are joined and joined once more among the cores."""
    names, at = xs(axes), _numbered(at, axes)
    counted = stage(close_pairs(at, axes, eps, ("w",)).groupBy("id", *names).agg(F.sum("y_w").alias("near")), "core")
    core = F.col("near") >= min_pts
    return _from_cores(counted.where(core).withColumn("node", F.col("id")), counted.where(~core), axes, eps)


def _dbscan_cells(at: DataFrame, axes: tuple[str, ...], eps: float, min_pts: int) -> DataFrame:
    """Cell summaries first: cells of side eps / sqrt(d) with enough points are all core.

    Only places of light cells count their neighbours, and dense cells link as cells, each
    named by its least place.
    """
    names, side = xs(axes), eps / len(axes) ** 0.5
    cells = [f"k{i}" for i in range(len(axes))]
    celled = _numbered(at, axes).withColumns({k: F.floor(F.col(x) / side).cast("bigint") for k, x in zip(cells, names)})
    dense = celled.groupBy(*cells).agg(F.sum("w").alias("held"), F.min("id").alias("node")).where(F.col("held") >= min_pts).drop("held")
    marked = stage(celled.join(dense, cells, "left").select("id", *names, "w", "node"), "cells")
    light = marked.where("node is null")
    counted = stage(close_pairs(light, axes, eps, ("w",), marked).groupBy("id", *names).agg(F.sum("y_w").alias("near")), "core")
    core = F.col("near") >= min_pts
    cores = marked.where("node is not null").select("id", *names, "node").unionByName(counted.where(core).select("id", *names, F.col("id").alias("node")))
    return _from_cores(cores, counted.where(~core), axes, eps)


def _pairs_within(x: np.ndarray, eps: float, limit: int = 4_000_000) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (i, j), i before j in cell order, within ``eps``, in portions of bounded size."""
    n, dim = x.shape
    cell = np.floor(x / eps).astype(np.int64)
    cell -= cell.min(0)
    span = cell.max(0) + 3
    steps = np.r_[np.cumprod(span[::-1])[::-1][1:], 1]
    code = (cell + 1) @ steps
    order = np.argsort(code, kind="stable")
    codes = code[order]
    for offset in product((-1, 0, 1), repeat=dim):
        if offset < (0,) * dim:
            continue
        wanted = codes + np.array(offset) @ steps
        low, high = np.searchsorted(codes, wanted), np.searchsorted(codes, wanted, side="right")
        if not any(offset):
            low = np.arange(n) + 1
        many = np.maximum(high - low, 0)
        upto = np.cumsum(many)
        start = 0
        while start < n:
            stop = max(start + 1, int(np.searchsorted(upto, (upto[start - 1] if start else 0) + limit)))
            part = many[start:stop]
            i = np.repeat(np.arange(start, min(stop, n)), part)
            j = np.repeat(low[start:stop] - np.cumsum(part) + part, part) + np.arange(part.sum())
            a, b = order[i], order[j]
            near = ((x[a] - x[b]) ** 2).sum(1) <= eps * eps
            yield a[near], b[near]
            start = stop


def _dbscan_blocks(at: DataFrame, axes: tuple[str, ...], eps: float, min_pts: int, side: int = 256) -> DataFrame:
    """Square blocks with a rim of two eps, each solved in one task, joined at shared cores.

    The rim makes the cores within eps of a block exact, so every edge of a block's own
    cores is seen there; a core in the rim of one block and inside another ties the two
    local clusters.
    """
    names, dim, width = xs(axes), len(axes), side * eps
    spread = at
    for i, x in enumerate(names):
        own = F.floor(F.col(x) / width).cast("bigint")
        rim = 2.001 * eps
        near = F.array_compact(F.array(own, F.when(F.col(x) - own * width <= rim, own - 1), F.when((own + 1) * width - F.col(x) <= rim, own + 1)))
        spread = spread.withColumn(f"o{i}", own).withColumn(f"b{i}", F.explode(near))
    own_block = F.lit(True)
    for i in range(dim):
        own_block = own_block & (F.col(f"o{i}") == F.col(f"b{i}"))
    blocks = [f"b{i}" for i in range(dim)]

    def solve(table: pa.Table) -> pa.Table:
        order = np.lexsort([table[x].to_numpy() for x in reversed(names)])
        x = np.stack([table[c].to_numpy() for c in names], 1)[order]
        w, own = table["w"].to_numpy()[order], table["own"].to_numpy(zero_copy_only=False)[order]
        low = np.array([table[b][0].as_py() for b in blocks]) * width
        inside = ((x >= low - 1.0005 * eps) & (x <= low + width + 1.0005 * eps)).all(1)
        count = w.astype(np.float64).copy()
        for a, b in _pairs_within(x, eps):
            count += np.bincount(a, w[b], len(x)) + np.bincount(b, w[a], len(x))
        core = inside & (count >= min_pts)
        label = np.arange(len(x))
        for a, b in _pairs_within(x, eps):
            both = core[a] & core[b]
            label = join_labels(label, a[both], b[both])
        edge_of, edge_to = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for a, b in _pairs_within(x, eps):
            for p, q in ((a, b), (b, a)):
                hit = own[p] & ~core[p] & core[q]
                pairs = np.unique(np.stack([p[hit], label[q[hit]]]), axis=1)
                edge_of.append(pairs[0])
                edge_to.append(pairs[1])
        cores = np.flatnonzero(core)
        who = np.concatenate([cores, *edge_of])
        root = np.concatenate([label[cores], *edge_to])
        kind = np.concatenate([np.where(own[cores], 0, 1), np.full(len(who) - len(cores), 2)])
        return pa.table({**{n: x[who, i] for i, n in enumerate(names)}, **{f"r{i}": x[root, i] for i in range(dim)}, "kind": kind.astype(np.int32)})

    schema = ", ".join([f"{n} double" for n in names] + [f"r{i} double" for i in range(dim)]) + ", kind int"
    local = stage(spread.withColumn("own", own_block).select(*names, "w", "own", *blocks).groupBy(*blocks).applyInArrow(solve, schema), "block")
    root = F.struct(*[F.col(f"r{i}").alias(f"x{i}") for i in range(dim)])
    rim = local.where("kind = 1").select(*names, root.alias("dst"))
    ties = local.where("kind = 0").select(*names, root.alias("src")).join(rim, names).where("src <> dst").select("src", "dst").distinct()
    roots = star_components(ties).select(F.col("node").alias("root"), F.col("root").alias("top"))
    named = local.where("kind <> 1").select(*names, root.alias("root")).join(roots, "root", "left").groupBy(*names).agg(F.min(F.coalesce("top", "root")).alias("root"))
    return number_roots(named, F.col("root"), axes)


def dbscan(points: DataFrame, axes: tuple[str, ...], eps: float, min_pts: int, engine: str = "blocks") -> DataFrame:
    """Places with ``min_pts`` points within ``eps``, themselves included, are cores.

    ``blocks`` solves squares locally, ``pairs`` joins all close pairs, ``cells`` goes by
    summaries of dense cells.  A border place takes the least of its clusters.
    """
    at = stage(places(points, axes), "place")
    run = {"blocks": _dbscan_blocks, "pairs": _dbscan_places, "cells": _dbscan_cells}[engine]
    return back(points, run(at, axes, eps, min_pts), axes)


def dbscan_multi(points: DataFrame, axes: tuple[str, ...], eps_list: list[float], min_pts: int) -> DataFrame:
    """Passes from the smallest eps up; each takes the points that earlier ones left."""
    left, out, base = points, None, 0
    for eps in sorted(eps_list):
        found = stage(dbscan(left, axes, eps, min_pts), "multi")
        kept = found.where("label is not null").withColumn("label", F.col("label") + base)
        base = (kept.agg(F.max("label")).first()[0] or base - 1) + 1
        out = kept if out is None else out.unionByName(kept)
        left = found.where("label is null").drop("label")
    return out.unionByName(left.withColumn("label", F.lit(None).cast("bigint")))


def mean_shift(points: DataFrame, axes: tuple[str, ...], bandwidth: float, iters: int = 30, tol: float = 1e-3) -> DataFrame:
    """Flat kernel from binned seeds: each seed moves to the mean within the bandwidth.

    Seeds that settle within a bandwidth of each other are one mode; a point goes to the
    nearest mode.
    """
    at = stage(places(points, axes), "place")
    names, dim = xs(axes), len(axes)
    bins = at.groupBy(*[F.floor(F.col(x) / bandwidth).alias(f"b{i}") for i, x in enumerate(names)]).agg(*[(F.sum(F.col(x) * F.col("w")) / F.sum("w")).alias(x) for x in names], F.sum("w").alias("w"))
    seeds = stage(bins.select(*names).withColumn("seed", F.struct(*names)), "seed")
    cells = at.withColumns({f"c{i}": F.floor(F.col(x) / bandwidth).cast("bigint") for i, x in enumerate(names)}).select(*[F.col(x).alias(f"y{i}") for i, x in enumerate(names)], "w", *[f"c{i}" for i in range(dim)])
    offsets = [tuple((k // 3**i) % 3 - 1 for i in range(dim)) for k in range(3**dim)]
    table = F.array(*[F.struct(*[F.lit(v).cast("bigint").alias(f"d{i}") for i, v in enumerate(o)]) for o in offsets])
    for _ in range(iters):
        around = seeds.withColumn("_o", F.explode(table)).withColumns({f"c{i}": F.floor(F.col(x) / bandwidth).cast("bigint") + F.col(f"_o.d{i}") for i, x in enumerate(names)})
        d2 = sum((F.pow(F.col(f"x{i}") - F.col(f"y{i}"), 2) for i in range(1, dim)), F.pow(F.col("x0") - F.col("y0"), 2))
        moved = around.join(cells, [f"c{i}" for i in range(dim)]).where(d2 <= bandwidth**2).groupBy("seed").agg(*[(F.sum(F.col(f"y{i}") * F.col("w")) / F.sum("w")).alias(f"m{i}") for i in range(dim)])
        step = sum((F.pow(F.col(f"x{i}") - F.col(f"m{i}"), 2) for i in range(1, dim)), F.pow(F.col("x0") - F.col("m0"), 2))
        after = stage(seeds.join(moved, "seed").select("seed", *[F.col(f"m{i}").alias(f"x{i}") for i in range(dim)], F.sqrt(step).alias("step")), "seed")
        far = after.agg(F.max("step")).first()[0] or 0.0
        seeds = after.drop("step")
        if far <= tol * bandwidth:
            break
    settled = stage(seeds.select(*names).distinct(), "mode")
    near = close_pairs(settled, axes, bandwidth).select(F.struct(*names).alias("src"), F.struct(*[F.col(f"y{i}").alias(f"x{i}") for i in range(dim)]).alias("dst"))
    roots = stage(star_components(near), "mode")
    modes = roots.select("root", *[F.col(f"node.{x}").alias(f"y{i}") for i, x in enumerate(names)])
    # a mode outside the 3^d cells around is farther than a cell's side: what lies within the
    # side is settled, and the others look again with cells twice as wide
    d2 = sum((F.pow(F.col(f"x{i}") - F.col(f"y{i}"), 2) for i in range(1, dim)), F.pow(F.col("x0") - F.col("y0"), 2))
    real = F.lit(True)
    for x in names:
        real = real & F.col(x).isNotNull() & ~F.isnan(x)
    side, left, placed = 2 * bandwidth, at.where(real).select(*names), None
    while not left.isEmpty():
        celled = modes.withColumns({f"c{i}": F.floor(F.col(f"y{i}") / side).cast("bigint") for i in range(dim)})
        home = left.withColumn("_o", F.explode(table)).withColumns({f"c{i}": F.floor(F.col(x) / side).cast("bigint") + F.col(f"_o.d{i}") for i, x in enumerate(names)})
        near = home.join(celled, [f"c{i}" for i in range(dim)]).where(d2 <= side**2)
        best = stage(near.groupBy(*names).agg(F.min_by("root", F.struct(d2, F.col("root"))).alias("root")), "near")
        placed = best if placed is None else placed.unionByName(best)
        left = stage(left.join(best, names, "left_anti"), "left")
        side *= 2
    if placed is None:
        return points.withColumn("label", F.lit(None).cast("bigint"))
    return back(points, number_roots(placed, F.col("root"), axes), axes)
