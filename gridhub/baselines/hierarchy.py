"""Hierarchical methods: linkage of all kinds, Ward, BIRCH."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.baselines.common import BaselineTooLarge, Nearest, back, collect_capped, labels_frame, number_roots, places, xs
from gridhub.baselines.density import _dbscan_blocks, dbscan
from gridhub.plans.staging import release, stage

LINKS = ("average", "single", "complete", "ward")


def _unions(n: int, merges: list[tuple[float, int, int]]) -> np.ndarray:
    """Group numbers of ``n`` leaves after the given merges of leaf pairs."""
    parent = np.arange(n)

    def find(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for _, a, b in merges:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return np.array([find(i) for i in range(n)], np.int64)


def merge_steps(x: np.ndarray, w: np.ndarray, link: str) -> list[tuple[float, int, int]]:
    """All merges of weighted points as (height, leaf, leaf), the cheapest first.

    Chains of nearest neighbours: follow the nearest group until two are each other's, and
    merge them; for these four links the order of such merges does not change the tree.
    """
    n = len(x)
    sq = (x**2).sum(1)
    d = np.maximum(sq[:, None] - 2 * x @ x.T + sq, 0)
    size = w.astype(float).copy()
    if link == "ward":
        d *= size[:, None] * size / (size[:, None] + size)
    else:
        np.sqrt(d, out=d)
    np.fill_diagonal(d, np.inf)
    alive, merges, chain = np.ones(n, bool), [], []
    for _ in range(n - 1):
        if not chain:
            chain.append(int(np.flatnonzero(alive)[0]))
        while True:
            a = chain[-1]
            row = d[a]
            b = int(row.argmin())
            if len(chain) > 1 and row[chain[-2]] <= row[b]:
                b = chain[-2]
                break
            chain.append(b)
        a = chain.pop()
        chain.pop()
        merges.append((float(d[a, b]), a, b))
        lo, hi = min(a, b), max(a, b)
        if link == "single":
            row = np.minimum(d[a], d[b])
        elif link == "complete":
            row = np.maximum(d[a], d[b])
        elif link == "average":
            row = (size[a] * d[a] + size[b] * d[b]) / (size[a] + size[b])
        else:
            row = ((size[a] + size) * d[a] + (size[b] + size) * d[b] - size * d[a, b]) / (size[a] + size[b] + size)
        row[~alive] = np.inf
        row[[a, b]] = np.inf
        d[lo], d[:, lo] = row, row
        d[hi], d[:, hi] = np.inf, np.inf
        size[lo] += size[hi]
        alive[hi] = False
    return sorted(merges, key=lambda m: m[0])


def ward_steps(x: np.ndarray, w: np.ndarray) -> list[tuple[float, int, int]]:
    """Ward's merges without a matrix: the cost of a merge follows from sizes and centres.

    Memory is linear; each step of a chain looks at the centres of all live groups, which
    are packed together again whenever half of them are gone.
    """
    centre, size = x.astype(float).copy(), w.astype(float).copy()
    leaf, live = np.arange(len(x)), np.ones(len(x), bool)
    merges, chain, left = [], [], len(x)
    while left > 1:
        if left * 2 < len(live):
            place = np.cumsum(live) - 1
            chain = [int(place[c]) for c in chain]
            centre, size, leaf = centre[live], size[live], leaf[live]
            live = np.ones(left, bool)
        if not chain:
            chain.append(int(live.argmax()))
        while True:
            a = chain[-1]
            far = centre[:, 0] - centre[a, 0]
            cost = far * far
            for j in range(1, centre.shape[1]):
                far = centre[:, j] - centre[a, j]
                cost += far * far
            cost *= size * size[a] / (size + size[a])
            cost[a] = np.inf
            cost[~live] = np.inf
            b = int(cost.argmin())
            if len(chain) > 1 and cost[chain[-2]] <= cost[b]:
                b = chain[-2]
                break
            chain.append(b)
        a = chain.pop()
        chain.pop()
        merges.append((float(cost[b]), int(leaf[a]), int(leaf[b])))
        lo, hi = min(a, b), max(a, b)
        centre[lo] = (size[a] * centre[a] + size[b] * centre[b]) / (size[a] + size[b])
        size[lo] += size[hi]
        live[hi] = False
        left -= 1
    return sorted(merges, key=lambda m: m[0])


def merge_tree(x: np.ndarray, w: np.ndarray, k: int, link: str) -> np.ndarray:
    """Labels after merging weighted points down to ``k`` groups."""
    return np.unique(_unions(len(x), merge_steps(x, w, link)[: max(0, len(x) - k)]), return_inverse=True)[1]


def linkage(points: DataFrame, axes: tuple[str, ...], k: int, link: str = "average", cap: int = 6_000) -> DataFrame:
    """One tree in one process over a matrix of all distances, of bounded size."""
    if link not in LINKS:
        raise ValueError(f"link is one of {LINKS}")
    x, w = collect_capped(points, axes, f"linkage {link}", cap)
    return labels_frame(points, axes, x, merge_tree(x, w, k, link))


def single_linkage_at(points: DataFrame, axes: tuple[str, ...], distance: float) -> DataFrame:
    """The single-linkage tree cut at a distance: components of the graph of close pairs.

    Distributed, without a matrix: every point is a core of a density search of one point.
    """
    return dbscan(points, axes, distance, 1)


def linkage_by_parts(points: DataFrame, axes: tuple[str, ...], k: int, link: str = "average", reach: float = 1.0, cap: int = 6_000) -> DataFrame:
    """Average, single or complete linkage to exactly ``k`` groups, as many trees as there are parts.

    Groups in different components of the graph of pairs within ``reach`` are farther apart
    than that under each of these links, so all merges up to that height happen inside the
    components, which are solved as tasks of their own.  The reach doubles until they leave
    at most ``k`` groups; the cheapest merges of all components then make the cut.  With
    fewer than ``k`` places each is a group.  A component of more than ``cap`` places has no
    exact tree within a task's memory: BaselineTooLarge.
    """
    if link not in LINKS[:3]:
        raise ValueError(f"link is one of {LINKS[:3]}")
    names = xs(axes)
    at = stage(places(points, axes), "place")
    total = at.count()

    def tree(table: pa.Table) -> pa.Table:
        x = np.stack([table[c].to_numpy() for c in names], 1)
        order = np.lexsort(x.T[::-1])
        steps = merge_steps(x[order], table["w"].to_numpy()[order], link)
        one = {"part": [table["part"][0].as_py()]} | {n: [x[order, i]] for i, n in enumerate(names)}
        return pa.table(one | {"height": [np.array([m[0] for m in steps], float)], "a": [np.array([m[1] for m in steps], np.int32)], "b": [np.array([m[2] for m in steps], np.int32)]}, schema=arrow)

    arrow = pa.schema([("part", pa.int64()), *[(n, pa.list_(pa.float64())) for n in names], ("height", pa.list_(pa.float64())), ("a", pa.list_(pa.int32())), ("b", pa.list_(pa.int32()))])
    kinds = ", ".join(["part long", *[f"{n} array<double>" for n in names], "height array<double>, a array<int>, b array<int>"])
    while True:
        parts = stage(_dbscan_blocks(at, tuple(names), reach, 1).withColumnRenamed("label", "part").join(at, names), "parts")
        count, most = parts.groupBy("part").agg(F.count("*").alias("n")).agg(F.count("*"), F.max("n")).first()
        if (most or 0) > cap:
            raise BaselineTooLarge(f"linkage {link}, a part", int(most), cap)
        # whole trees, of which the merges up to the limit hold; parts that stay apart at a
        # larger reach keep theirs
        trees = stage(parts.groupBy("part").applyInArrow(tree, kinds), "trees")
        limit = reach if count > 1 else math.inf  # one component has the whole tree
        while True:
            merges = trees.select("part", F.posexplode("height").alias("nth", "height")).where(F.col("height") <= limit)
            groups = total - merges.count()
            if groups <= k or count <= 1 or not _parts_apart(trees, names, 2 * limit):
                break
            limit *= 2
        if groups <= k or count <= 1:
            break
        release(parts, trees)
        reach = 2 * limit
    # the dearest merges are left out, as many as groups are lacking: k rows at most
    spare = merges.orderBy(F.desc("height"), F.desc("part"), F.desc("nth")).limit(max(0, min(k, total) - groups))
    left_out = spare.groupBy("part").agg(F.count("*").alias("spare"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                x = [batch.column(n)[row].values.to_numpy() for n in names]
                height, a, b = (batch.column(c)[row].values.to_numpy() for c in ("height", "a", "b"))
                kept = int((height <= limit).sum()) - batch.column("spare")[row].as_py()
                root = _unions(len(x[0]), list(zip(height[:kept], a[:kept].tolist(), b[:kept].tolist())))
                yield pa.RecordBatch.from_pydict({n: v for n, v in zip(names, x)} | {f"r{i}": v[root] for i, v in enumerate(x)})

    schema = ", ".join([f"{n} double" for n in names] + [f"r{i} double" for i in range(len(names))])
    labelled = trees.join(left_out, "part", "left").withColumn("spare", F.coalesce("spare", F.lit(0))).mapInArrow(cut, schema)
    return back(points, number_roots(labelled, F.struct(*[f"r{i}" for i in range(len(names))]), axes), axes)


def _parts_apart(trees: DataFrame, names: list[str], gap: float) -> bool:
    """Whether the boxes around the parts are all farther apart than ``gap``."""
    boxes = trees.select("part", *[F.array_min(n).alias(f"lo_{n}") for n in names], *[F.array_max(n).alias(f"hi_{n}") for n in names])
    wide = boxes.agg(F.greatest(F.lit(0.0), *[F.max(F.col(f"hi_{n}") - F.col(f"lo_{n}")) for n in names])).first()[0]
    side = 1.001 * (wide + gap)
    mine = boxes.withColumns({f"c{i}": F.floor(F.col(f"lo_{n}") / side).cast("bigint") for i, n in enumerate(names)})
    other = boxes.select(*[F.col(c).alias(f"o_{c}") for c in boxes.columns])
    for i, n in enumerate(names):
        first, last = (F.floor((F.col(f"o_{end}_{n}") + d) / side).cast("bigint") for end, d in (("lo", -side), ("hi", 1.001 * gap)))
        other = other.withColumn(f"c{i}", F.explode(F.sequence(first, last)))
    between = lambda n: F.greatest(F.lit(0.0), F.col(f"lo_{n}") - F.col(f"o_hi_{n}"), F.col(f"o_lo_{n}") - F.col(f"hi_{n}"))
    d2 = sum((between(n) * between(n) for n in names[1:]), between(names[0]) * between(names[0]))
    return mine.join(other, [f"c{i}" for i in range(len(names))]).where((F.col("part") < F.col("o_part")) & (d2 <= gap * gap * (1 + 1e-9))).isEmpty()


def single_linkage(points: DataFrame, axes: tuple[str, ...], k: int, reach: float = 1.0, cap: int = 6_000) -> DataFrame:
    """Single linkage to exactly ``k`` groups, part by part."""
    return linkage_by_parts(points, axes, k, "single", reach, cap)


def ward(points: DataFrame, axes: tuple[str, ...], k: int, cap: int = 100_000) -> DataFrame:
    """Ward's groups of a bounded number of points, in linear memory."""
    x, w = collect_capped(points, axes, "ward", cap)
    labels = np.unique(_unions(len(x), ward_steps(x, w)[: max(0, len(x) - k)]), return_inverse=True)[1]
    return labels_frame(points, axes, x, labels)


class _FeatureTree:
    """Clustering features (count, sum, square sum) in a tree of bounded branching."""

    def __init__(self, threshold: float, branching: int, dim: int):
        self.t2, self.branching, self.dim = threshold**2, branching, dim
        self.root = self._node([], None)

    def _node(self, entries: list, children: list | None) -> list:
        """Features of the entries, children or None, and the entries' centres."""
        at = np.full((self.branching + 1, self.dim), np.inf)
        for i, e in enumerate(entries):
            at[i] = e[1] / e[0]
        return [entries, children, at]

    @staticmethod
    def _put(node: list, i: int, feature: tuple) -> None:
        node[0][i] = feature
        node[2][i] = feature[1] / feature[0]

    def _insert(self, node: list, n: float, s: np.ndarray, q: float):
        entries, children, at = node
        if entries:
            far = at - s / n
            i = int(np.einsum("ij,ij->i", far, far).argmin())
            m, ms, mq = entries[i]
            both = (m + n, ms + s, mq + q)
            if children is None:
                spread = both[2] / both[0] - ((both[1] / both[0]) ** 2).sum()
                if spread <= self.t2:
                    self._put(node, i, both)
                    return None
            else:
                split = self._insert(children[i], n, s, q)
                if split is None:
                    self._put(node, i, both)
                    return None
                entries[i : i + 1] = [self._sum(c) for c in split]
                children[i : i + 1] = split
                node[2] = self._node(entries, children)[2]
                return self._split(node) if len(entries) > self.branching else None
        entries.append((n, s, q))
        at[len(entries) - 1] = s / n
        return self._split(node) if len(entries) > self.branching else None

    @staticmethod
    def _sum(node: list):
        return sum(e[0] for e in node[0]), sum(e[1] for e in node[0]), sum(e[2] for e in node[0])

    def _split(self, node: list) -> list:
        entries, children, at = node
        at = at[: len(entries)]
        d2 = ((at[:, None] - at[None]) ** 2).sum(2)
        a, b = np.unravel_index(d2.argmax(), d2.shape)
        left = d2[:, a] <= d2[:, b]
        if left.all():
            left[len(left) // 2 :] = False
        pick = lambda m: self._node([e for e, k in zip(entries, m) if k], None if children is None else [c for c, k in zip(children, m) if k])
        return [pick(left), pick(~left)]

    def add(self, n: float, s: np.ndarray, q: float) -> None:
        split = self._insert(self.root, n, s, q)
        if split:
            self.root = self._node([self._sum(c) for c in split], split)

    def leaves(self) -> list:
        out, stack = [], [self.root]
        while stack:
            entries, children, _ = stack.pop()
            if children is None:
                out += entries
            else:
                stack += children
        return out


def birch(points: DataFrame, axes: tuple[str, ...], threshold: float, branching: int = 50, k: int | None = None) -> DataFrame:
    """Feature trees of neighbouring points, merged in one tree, then Ward over the features.

    Points are dealt by coarse cells, so what leaves the tasks is about as many features as
    the plane holds, and only they come to the driver: linear memory, no matrix.
    """
    dim = len(axes)
    schema = "n double, " + ", ".join(f"s{i} double" for i in range(dim)) + ", q double"

    def build(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tree = _FeatureTree(threshold, branching, dim)
        for pdf in batches:
            for p in pdf.to_numpy(float):
                tree.add(1.0, p, float(p @ p))
        rows = [[n, *s, q] for n, s, q in tree.leaves()]
        yield pd.DataFrame(rows, columns=["n", *[f"s{i}" for i in range(dim)], "q"])

    rows = points.select(*[F.col(a).cast("double").alias(a) for a in axes])
    coarse = [F.floor(F.col(a) / (32 * threshold)) for a in axes]
    found = stage(rows.repartition(*coarse).sortWithinPartitions(*coarse, *axes).mapInPandas(build, schema), "feature")
    features = found.toPandas().sort_values(["s0", "n"]).to_numpy()
    tree = _FeatureTree(threshold, branching, dim)
    for f in features:
        tree.add(f[0], f[1 : 1 + dim], f[-1])
    merged = tree.leaves()
    centres = np.array([s / n for n, s, _ in merged])
    weight = np.array([n for n, _, _ in merged])
    labels = np.arange(len(centres)) if k is None else np.unique(_unions(len(centres), ward_steps(centres, weight)[: max(0, len(centres) - k)]), return_inverse=True)[1]
    near = Nearest(centres)

    @F.pandas_udf("bigint")
    def label(*cols: pd.Series) -> pd.Series:
        return pd.Series(labels[near.find(np.column_stack([c.to_numpy(float) for c in cols]))[0]])

    return points.withColumn("label", label(*[F.col(a).cast("double") for a in axes]))
