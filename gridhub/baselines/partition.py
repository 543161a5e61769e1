"""Partitioning methods: k-means and its mini-batch form, mixtures, spectral, affinity."""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.ml.clustering import PowerIterationClustering
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.baselines.common import Nearest, _grid, _spans, _two_axes, back, close_pairs, collect_capped, labels_frame, places, xs
from gridhub.plans.staging import release, stage


def _scan(points: DataFrame, axes: tuple[str, ...]) -> DataFrame:
    return points.select(*[F.col(a).cast("double").alias(x) for a, x in zip(axes, xs(axes))])


#: Points of a block, and points of a file of blocks.
BLOCK, FILE = 1 << 15, 1 << 18


def _blocks(rows: DataFrame) -> DataFrame:
    """All rows once more on disk, along a Z curve over their first two axes.

    A row holds up to ``BLOCK`` of them, axis by axis, as the bytes of doubles.  The curve
    has 2^26 steps an axis; ten more bits of the key deal out rows of one step.
    """
    names = rows.columns
    flat = names[:2]
    ends = rows.agg(F.count("*"), *[f(x) for x in flat for f in (F.min, F.max)]).first()
    spread = [("16", "0x0000FFFF0000FFFF"), ("8", "0x00FF00FF00FF00FF"), ("4", "0x0F0F0F0F0F0F0F0F"), ("2", "0x3333333333333333"), ("1", "0x5555555555555555")]
    keyed = rows.withColumn("_key", F.monotonically_increasing_id().bitwiseAND(F.lit(1023)))
    for i, x in enumerate(flat):
        low, high = ends[1 + 2 * i], ends[2 + 2 * i]
        wide = high - low if low is not None and high > low else 1.0
        keyed = keyed.withColumn("_q", F.floor((F.col(x) - F.lit(low)) / F.lit(wide) * F.lit((1 << 26) - 1)).cast("bigint"))
        for by, mask in spread:
            keyed = keyed.withColumn("_q", F.expr(f"(_q | shiftleft(_q, {by})) & {int(mask, 16)}L"))
        keyed = keyed.withColumn("_key", F.expr(f"_key | shiftleft(_q, {10 + i})"))
    parts = max(-(-ends[0] // FILE), min(rows.sparkSession.sparkContext.defaultParallelism, -(-ends[0] // BLOCK)), 1)
    laid = keyed.select("_key", *names).repartitionByRange(parts, "_key").sortWithinPartitions("_key").select(*names)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in itertools.chain(batches, [None]):
            if batch is not None:
                held.append(np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]))
                n += batch.num_rows
            if n >= BLOCK or batch is None and n:
                x = np.concatenate(held, 1)
                whole = n if batch is None else n - n % BLOCK
                yield pa.RecordBatch.from_pydict({"x": [np.ascontiguousarray(x[:, i : min(i + BLOCK, whole)]).tobytes() for i in range(0, whole, BLOCK)]})
                held, n = [x[:, whole:]], n - whole

    return stage(laid.mapInArrow(pack, "x binary"), "blocks", "none")


def _unpacked(batches: Iterator[pa.RecordBatch], dim: int) -> Iterator[np.ndarray]:
    for batch in batches:
        for x in batch.column(0):
            yield np.frombuffer(x.as_buffer(), float).reshape(dim, -1).T


def _moments(blocks: DataFrame, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Rows and coordinate sums by nearest centre, and the cost.

    A task returns a row for each centre that it met; tasks hold neighbouring rows, so few
    centres are met by several.
    """
    k, dim = centres.shape
    names = ["w", *[f"s{i}" for i in range(dim)], "cost"]
    sent = blocks.sparkSession.sparkContext.broadcast(Nearest(centres))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near, total = sent.value, np.zeros((len(names), k))
        for x in _unpacked(batches, dim):
            cell, d2 = near.along(x)
            for sums, weights in zip(total, (None, *x.T, d2)):
                sums += np.bincount(cell, weights, k)
        hit = np.flatnonzero(total[0])
        yield pa.RecordBatch.from_pydict({"c": hit, **{n: sums[hit] for n, sums in zip(names, total)}})

    found = blocks.mapInArrow(run, "c bigint, " + ", ".join(f"{n} double" for n in names)).toArrow()
    sent.destroy()
    w, *s, cost = (np.bincount(found["c"].to_numpy(), found[n].to_numpy(), k) for n in names)
    return w, np.stack(s, 1), float(cost.sum())


def _oversampled(blocks: DataFrame, dim: int, k: int, seed: int, rounds: int = 5) -> np.ndarray:
    """Candidates for centres: each round draws some 2k of all rows by their squared distance."""
    centres = np.stack([x[:1] for x in _unpacked(blocks.limit(1).toArrow().to_batches(), dim)]).reshape(-1, dim)
    for turn in range(rounds):
        cost = _moments(blocks, centres)[2]
        if cost <= 0:
            break
        sent = blocks.sparkSession.sparkContext.broadcast(Nearest(centres))

        def draw(batches: Iterator[pa.RecordBatch], sent=sent, cost=cost, turn=turn) -> Iterator[pa.RecordBatch]:
            rng = np.random.default_rng([seed, turn, TaskContext.get().partitionId()])
            for x in _unpacked(batches, dim):
                drawn = x[rng.random(len(x)) * cost < 2 * k * sent.value.along(x)[1]]
                yield pa.RecordBatch.from_pydict({f"x{i}": drawn[:, i] for i in range(dim)})

        drawn = blocks.mapInArrow(draw, ", ".join(f"x{i} double" for i in range(dim))).toArrow()
        sent.destroy()
        centres = np.unique(np.r_[centres, np.stack([c.to_numpy() for c in drawn.columns], 1)], axis=0)
    return centres


def kmeans(points: DataFrame, axes: tuple[str, ...], k: int, seed: int = 1, iters: int = 40, tol: float = 1e-4) -> DataFrame:
    """Lloyd's rounds over all points, from k of the candidates of an oversampling start.

    The points are laid out by their place once; a round reads every one of them.  Nearest
    centres are exact, found for runs of points by a grid.  Ends when no centre moves by more
    than ``tol``.
    """
    blocks = _blocks(_scan(points, axes))
    candidates = _oversampled(blocks, len(axes), k, seed)
    weight = _moments(blocks, candidates)[0]
    held = weight > 0
    candidates, weight = candidates[held], weight[held]
    centres = _spread_start(candidates, k, np.random.default_rng(seed), weight)
    for _ in range(30):  # the candidates by their weights first
        cell, before = Nearest(centres).find(candidates)[0], centres
        total = np.bincount(cell, weight, len(centres))
        sums = np.stack([np.bincount(cell, weight * candidates[:, i], len(centres)) for i in range(len(axes))], 1)
        centres = np.where(total[:, None] > 0, sums / np.maximum(total, 1e-300)[:, None], centres)
        if ((centres - before) ** 2).sum(1).max() <= tol * tol:
            break
    for _ in range(iters):
        w, s, _ = _moments(blocks, centres)
        before, centres = centres, np.where(w[:, None] > 0, s / np.maximum(w, 1)[:, None], centres)
        if ((centres - before) ** 2).sum(1).max() <= tol * tol:
            break
    release(blocks)
    return _assign(points, axes, centres)


class Mixture:
    """Gaussians on a grid: a point meets those whose share of it is not zero in doubles.

    A share less than ``exp(-ZERO)`` of the largest is zero.  A Gaussian of largest variance
    ``v`` and peak ``a`` stays below that at points farther than ``sqrt(2 v (a + FLOOR +
    ZERO))``, if the point's largest log density is at least ``-FLOOR``; so it is listed in
    the cells within that reach, and points of a lower density meet all Gaussians.
    """

    ZERO, FLOOR, TABLE = 746.0, 200.0, 1_000_000

    def __init__(self, weight: np.ndarray, mean: np.ndarray, cov: np.ndarray):
        self.weight, self.mean = weight, mean
        low = np.linalg.cholesky(cov)
        self.turn = np.linalg.inv(low)
        self.peak = np.log(weight + 1e-300) - np.log(np.diagonal(low, axis1=1, axis2=2)).sum(1)
        reach = np.sqrt(np.maximum(2 * np.linalg.eigvalsh(cov)[:, -1] * (self.peak + self.FLOOR + self.ZERO), 0)) * (1 + 1e-9)
        flat = _two_axes(mean)
        self.low, self.side, self.shape = _grid(flat, len(mean))
        ends = [np.clip(np.floor((flat + d * reach[:, None] - self.low) / self.side), 0, np.array(self.shape) - 1).astype(np.int64) for d in (-1, 1)]
        wide = ends[1] - ends[0] + 1
        many = wide.prod(1)
        which = np.repeat(np.arange(len(mean)), many)
        nth = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        code = (ends[0][which, 0] + nth // wide[which, 1]) * self.shape[1] + ends[0][which, 1] + nth % wide[which, 1]
        order = np.argsort(code, kind="stable")
        self.listed = which[order].astype(np.int32)
        self.starts = np.searchsorted(code[order], np.arange(self.shape[0] * self.shape[1] + 1))

    def _logs(self, x: np.ndarray, at: np.ndarray, c: np.ndarray) -> np.ndarray:
        far, out = x[at] - self.mean[c], self.peak[c].copy()
        for i in range(x.shape[1]):
            z = sum(self.turn[c, i, j] * far[:, j] for j in range(i + 1))
            out -= 0.5 * z * z
        return out

    def logs(self, x: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """(point, Gaussian, log, start of each point's rows) of all pairs that may matter."""
        cell = np.floor((_two_axes(x) - self.low) / self.side)
        out = ((cell < 0) | (cell >= self.shape)).any(1)
        code = np.where(out, 0, cell[:, 0] * self.shape[1] + cell[:, 1]).astype(np.int64)
        held = np.where(out, 0, self.starts[code + 1] - self.starts[code])
        left, listed = [np.flatnonzero(held == 0)], np.flatnonzero(held)
        for part in np.split(listed, np.flatnonzero(np.diff(np.cumsum(held[listed]) // self.TABLE)) + 1):
            if not len(part):
                continue
            at = np.repeat(part, held[part])
            first = np.cumsum(held[part]) - held[part]
            c = self.listed[np.repeat(self.starts[code[part]] - first, held[part]) + np.arange(len(at))]
            logs = self._logs(x, at, c)
            sure = np.maximum.reduceat(logs, first) >= -self.FLOOR
            left.append(part[~sure])
            rows = np.repeat(sure, held[part])
            if rows.any():
                yield at[rows], c[rows], logs[rows], np.cumsum(held[part][sure]) - held[part][sure]
        left, k = np.concatenate(left), len(self.mean)
        for i in range(0, len(left), max(1, self.TABLE // k)):
            part = left[i : i + max(1, self.TABLE // k)]
            at, c = np.repeat(part, k), np.tile(np.arange(k), len(part))
            yield at, c, self._logs(x, at, c), np.arange(len(part)) * k

    def shares(self, x: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, float]]:
        """(point, Gaussian, share, log likelihood of these points)."""
        for at, c, logs, first in self.logs(x):
            many = np.diff(np.r_[first, len(at)])
            top = np.maximum.reduceat(logs, first)
            r = np.exp(logs - np.repeat(top, many))
            total = np.add.reduceat(r, first)
            yield at, c, r / np.repeat(total, many), float((top + np.log(total)).sum())

    def best(self, x: np.ndarray) -> np.ndarray:
        """The likeliest Gaussian of every point, of several the first."""
        out = np.zeros(len(x), np.int64)
        for at, c, logs, first in self.logs(x):
            many = np.diff(np.r_[first, len(at)])
            likely = np.where(logs == np.repeat(np.maximum.reduceat(logs, first), many), c, len(self.mean))
            out[at[first]] = np.minimum.reduceat(likely, first)
        return out


def gaussian_mixture(points: DataFrame, axes: tuple[str, ...], k: int, seed: int = 1, iters: int = 40, tol: float = 1e-4, ridge: float = 1e-6) -> DataFrame:
    """Expectation maximisation for k full Gaussians, from spread-out mini-batch centres.

    Each task sums its responsibilities; the driver adds k rows per task and round.
    """
    dim = len(axes)
    start = minibatch_kmeans(points, axes, k, seed=seed)
    cols = [F.col(a).cast("double") for a in axes]
    first = start.groupBy("label").agg(F.count("*").alias("w"), *[F.avg(c).alias(f"m{i}") for i, c in enumerate(cols)], *[F.coalesce(F.var_samp(c), F.lit(0.0)).alias(f"v{i}") for i, c in enumerate(cols)]).orderBy("label").toPandas()
    weight = first["w"].to_numpy(float) / first["w"].sum()
    mean = first[[f"m{i}" for i in range(dim)]].to_numpy()
    floor = ridge * max(1e-12, float(first[[f"v{i}" for i in range(dim)]].to_numpy().mean()))
    cov = np.stack([np.diag(v + floor) for v in first[[f"v{i}" for i in range(dim)]].to_numpy()])

    names = ["c", "w", *[f"s{i}" for i in range(dim)], *[f"q{i}" for i in range(dim * dim)], "ll"]
    rows = points.select(*[c.alias(f"x{i}") for i, c in enumerate(cols)])
    before = -np.inf
    for _ in range(iters):
        model = (weight, mean, cov)

        def expect(batches, model=Mixture(*model)):
            k = len(model.weight)
            w, s, q, ll = np.zeros(k), np.zeros((dim, k)), np.zeros((dim, dim, k)), 0.0
            for pdf in batches:
                x = pdf.to_numpy(float)
                for at, c, r, total in model.shares(x):
                    ll += total
                    w += np.bincount(c, r, k)
                    for i in range(dim):
                        s[i] += np.bincount(c, r * x[at, i], k)
                        for j in range(dim):
                            q[i, j] += np.bincount(c, r * x[at, i] * x[at, j], k)
            yield pd.DataFrame({"c": np.arange(k), "w": w} | {f"s{i}": s[i] for i in range(dim)} | {f"q{i}": q[i // dim, i % dim] for i in range(dim * dim)} | {"ll": np.r_[ll, np.zeros(k - 1)]})[names]

        sums = rows.mapInPandas(expect, "c bigint, " + ", ".join(f"{n} double" for n in names[1:])).groupBy("c").agg(*[F.sum(n).alias(n) for n in names[1:]]).orderBy("c").toPandas()
        w = np.maximum(sums["w"].to_numpy(), 1e-9)
        mean = sums[[f"s{i}" for i in range(dim)]].to_numpy() / w[:, None]
        cov = sums[[f"q{i}" for i in range(dim * dim)]].to_numpy().reshape(-1, dim, dim) / w[:, None, None] - mean[:, :, None] * mean[:, None, :] + floor * np.eye(dim)
        weight, now = w / w.sum(), float(sums["ll"].sum())
        if abs(now - before) <= tol * abs(now):
            break
        before = now
    final = Mixture(weight, mean, cov)

    @F.pandas_udf("bigint")
    def best(*xcols: pd.Series) -> pd.Series:
        return pd.Series(final.best(np.column_stack([c.to_numpy(float) for c in xcols])))

    return points.withColumn("label", best(*cols))


def _spread_start(x: np.ndarray, k: int, rng: np.random.Generator, weight: np.ndarray | None = None, trials: int = 8) -> np.ndarray:
    """Centres drawn one by one, each by its squared distance to those before.

    Of some trials the one that lowers the cost most is taken.  Points are held cell by
    cell: a trial can only bear on cells within the largest distance of any point, and a
    draw takes a slab of cells first, then the cell.  The trials are weighed side by side
    while they bear on few points.
    """
    flat = _two_axes(x)
    low, side, (nx, ny) = _grid(flat, max(1, min(k, len(x))))
    cell = np.floor((flat - low) / side).astype(np.int64)
    code = cell[:, 0] * ny + cell[:, 1]
    order = np.argsort(code, kind="stable")
    code, starts = code[order], np.searchsorted(code[order], np.arange(nx * ny + 1))
    x, flat, w = x[order], flat[order], np.ones(len(x)) if weight is None else weight[order]
    centres = [x[rng.integers(len(x))]]
    d2 = ((x - centres[0]) ** 2).sum(1)
    slab = int(np.sqrt(nx * ny)) + 1
    mass = np.zeros((-(-nx * ny // slab), slab))
    mass.ravel()[: nx * ny] = np.bincount(code, w * d2, nx * ny)
    slabs = mass.sum(1)

    def drawn() -> np.ndarray:
        upto = np.cumsum(slabs)
        u = rng.random(trials) * upto[-1]
        s = np.minimum(np.searchsorted(upto, u, "right"), len(slabs) - 1)
        inner = np.cumsum(mass[s], 1)
        c = s * slab + np.minimum((inner <= (u - upto[s] + slabs[s])[:, None]).sum(1), slab - 1)
        for i in np.flatnonzero(~(mass.ravel()[c] > 0)):  # past the end by rounding
            c[i] = np.flatnonzero(mass.ravel()[: c[i]] > 0)[-1] if (mass.ravel()[: c[i]] > 0).any() else np.argmax(mass)
        held = starts[c + 1] - starts[c]
        rows, first = _spans(starts[c], held), np.cumsum(held) - held
        upto = np.cumsum(w[rows] * d2[rows])
        before = np.r_[0.0, upto][first]
        t = np.searchsorted(upto, before + rng.random(trials) * (upto[first + held - 1] - before), "right")
        return rows[np.clip(t, first, first + held - 1)]

    def lines_near(t: np.ndarray, reach: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(trial, first cell, end) of each line of cells within reach."""
        ends = np.array([nx, ny]) - 1
        a, b = (np.clip(np.floor((flat[t] + d - low) / side), 0, ends).astype(np.int64) for d in (-reach, reach))
        lines = b[:, 0] - a[:, 0] + 1
        trial = np.repeat(np.arange(len(t)), lines)
        first = _spans(a[:, 0], lines) * ny
        return trial, first + a[trial, 1], first + b[trial, 1] + 1

    while len(centres) < k:
        if len(centres) % 16 == 1:
            reach = float(np.sqrt(d2.max())) * (1 + 1e-9)  # distances only fall
        if not slabs.sum() > 0:
            break
        t, best = drawn(), None
        trial, begin, end = lines_near(t, reach)
        lot = np.arange(trials) if (starts[end] - starts[begin]).sum() < 1 << 16 else None
        for some in [lot] if lot is not None else np.arange(trials)[:, None]:
            on = slice(None) if lot is not None else trial == some[0]
            a, b = begin[on], end[on]
            held = starts[b] - starts[a]
            rows, of = _spans(starts[a], held), np.repeat(trial[on], held)
            fresh = np.minimum(((x[rows] - x[t[of]]) ** 2).sum(1), d2[rows])
            gains = np.bincount(of, w[rows] * (d2[rows] - fresh), trials)[some]
            top = int(some[gains.argmax()])
            if best is None or gains.max() > best[0]:
                mine = of == top
                best = gains.max(), top, rows[mine], fresh[mine], a[trial[on] == top], b[trial[on] == top]
        _, top, rows, fresh, a, b = best
        centres.append(x[t[top]])
        d2[rows] = fresh
        cells, sizes = _spans(a, b - a), b - a
        shift = np.repeat((np.cumsum(sizes) - sizes) - a, starts[b] - starts[a])
        mass.ravel()[cells] = np.bincount(code[rows] + shift, w[rows] * fresh, len(cells))
        touched = np.unique(cells // slab)
        slabs[touched] = mass[touched].sum(1)
    return np.array(centres)


def _assign(points: DataFrame, axes: tuple[str, ...], centres: np.ndarray) -> DataFrame:
    """Nearest centre per Arrow batch; the centres are k rows in the closure."""
    near = Nearest(centres)

    @F.pandas_udf("bigint")
    def nearest(*cols: pd.Series) -> pd.Series:
        return pd.Series(near.find(np.column_stack([c.to_numpy(float) for c in cols]))[0])

    return points.withColumn("label", nearest(*[F.col(a).cast("double") for a in axes]))


def minibatch_kmeans(points: DataFrame, axes: tuple[str, ...], k: int, batch: int = 1024, iters: int = 100, starts: int = 3, seed: int = 1) -> DataFrame:
    """Centres move by 1/count towards each batch; every batch is drawn from all the data.

    One scan draws the rows of all batches, ``iters * batch`` of them, whatever the input;
    each start deals them into batches anew.
    """
    need = max(iters * batch, 20 * k)
    rows = points.count()
    drawn = points if rows <= need else points.sample(min(1.0, need / rows), seed)
    x = drawn.select(*[F.col(a).cast("double") for a in axes]).toPandas().to_numpy()
    best, best_cost = None, np.inf
    for start in range(starts):
        rng = np.random.default_rng([seed, start])
        centres = _spread_start(x, k, rng)
        seen, order = np.zeros(len(centres)), rng.permutation(len(x))
        for turn in range(iters):
            some = x[order[np.arange(turn * batch, (turn + 1) * batch) % len(x)]] if len(x) else x
            cell = Nearest(centres).find(some)[0]
            many = np.bincount(cell, minlength=len(centres))
            sums = np.stack([np.bincount(cell, some[:, j], len(centres)) for j in range(x.shape[1])], 1)
            hit = many > 0
            seen += many
            centres[hit] += (sums[hit] - many[hit, None] * centres[hit]) / seen[hit, None]
        cost = Nearest(centres).find(x)[1].sum()
        if cost < best_cost:
            best, best_cost = centres, cost
    return _assign(points, axes, best)


def affinity_propagation(points: DataFrame, axes: tuple[str, ...], damping: float = 0.9, preference: float | None = None, iters: int = 400, cap: int = 6_000) -> DataFrame:
    """Messages between all pairs of places until exemplars settle; n^2 memory, capped."""
    x, w = collect_capped(points, axes, "affinity propagation", cap)
    n = len(x)
    s = -(((x**2).sum(1)[:, None] - 2 * x @ x.T + (x**2).sum(1)).astype(np.float32))
    np.fill_diagonal(s, np.median(s) if preference is None else preference)
    s += np.random.default_rng(0).normal(0, 1e-9 * (abs(s).max() + 1e-30), s.shape).astype(np.float32)
    r, a = np.zeros_like(s), np.zeros_like(s)
    row, settled, before = np.arange(n), 0, None
    for _ in range(iters):
        both = a + s
        top = both.argmax(1)
        first = both[row, top]
        both[row, top] = -np.inf
        new = s - first[:, None]
        new[row, top] = s[row, top] - both.max(1)
        r = damping * r + (1 - damping) * new
        p = np.maximum(r, 0)
        p[row, row] = r[row, row]
        new = p.sum(0)[None, :] - p
        diagonal = new[row, row].copy()
        new = np.minimum(new, 0)
        new[row, row] = diagonal
        a = damping * a + (1 - damping) * new
        chosen = (r[row, row] + a[row, row]) > 0
        settled = settled + 1 if before is not None and (chosen == before).all() else 0
        before = chosen
        if settled >= 15 and chosen.any():
            break
    exemplars = np.flatnonzero(before)
    labels = s[:, exemplars].argmax(1) if len(exemplars) else np.zeros(n, int)
    labels[exemplars] = np.arange(len(exemplars))
    return labels_frame(points, axes, x, labels)


def spectral(points: DataFrame, axes: tuple[str, ...], k: int, knn: int = 40, seed: int = 1, cap: int = 12_000) -> DataFrame:
    """Nearest-neighbour graph, top eigenvectors of its normalised matrix, k-means on them.

    The graph is held as a sparse edge list; the n x k vectors and the pair search are what
    the cap is for.
    """
    x, _ = collect_capped(points, axes, "spectral", cap)
    n, rng = len(x), np.random.default_rng(seed)
    sides = []
    for i in range(0, n, 1024):
        d2 = ((x[i : i + 1024, None] - x[None]) ** 2).sum(2)
        sides.append(np.argpartition(d2, min(knn, n - 1), axis=1)[:, : knn + 1])
    near = np.concatenate(sides)
    a, b = np.repeat(np.arange(n), near.shape[1]), near.ravel()
    a, b = np.r_[a, b], np.r_[b, a]
    weight = np.full(len(a), 0.5)
    degree = np.bincount(a, weight, n)
    scale = weight / np.sqrt(degree[a] * degree[b])

    def times(v: np.ndarray) -> np.ndarray:
        return np.stack([np.bincount(a, scale * v[b, j], n) for j in range(v.shape[1])], 1) + v

    q = np.linalg.qr(rng.normal(size=(n, min(n, k + 4))))[0]
    for _ in range(150):
        q = np.linalg.qr(times(q))[0]
    values, vectors = np.linalg.eigh(q.T @ times(q))
    top = (q @ vectors)[:, np.argsort(-values)[:k]]
    top /= np.maximum(np.linalg.norm(top, axis=1, keepdims=True), 1e-12)
    best, cost = None, np.inf
    for start in range(5):
        centres = _spread_start(top, k, np.random.default_rng([seed, start]))
        for _ in range(50):
            cell = ((centres**2).sum(1) - 2 * top @ centres.T).argmin(1)
            centres = np.stack([top[cell == c].mean(0) if (cell == c).any() else centres[c] for c in range(len(centres))])
        now = ((top - centres[cell]) ** 2).sum()
        if now < cost:
            best, cost = cell, now
    return labels_frame(points, axes, x, best)


def power_iteration(points: DataFrame, axes: tuple[str, ...], k: int, eps: float, iters: int = 30) -> DataFrame:
    """The distributed relative of the spectral method, on the graph of close pairs."""
    at = stage(places(points, axes).withColumn("id", F.monotonically_increasing_id()), "place")
    pairs = close_pairs(at, axes, eps, ("id",)).where("id < y_id").select(F.col("id").alias("src"), F.col("y_id").alias("dst"), F.exp(-F.col("d2") / (eps * eps)).alias("weight"))
    found = PowerIterationClustering(k=k, maxIter=iters, weightCol="weight").assignClusters(stage(pairs, "pic"))
    return back(points, at.join(found, "id").select(*xs(axes), F.col("cluster").cast("bigint").alias("label")), axes)
