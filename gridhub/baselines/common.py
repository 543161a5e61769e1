"""What the baselines share."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


class BaselineTooLarge(Exception):
    """A method refuses an input that its memory cannot hold."""

    def __init__(self, method: str, rows: int, cap: int):
        super().__init__(f"{method}: {rows} rows, at most {cap}")
        self.method, self.rows, self.cap = method, rows, cap


def places(points: DataFrame, axes: tuple[str, ...]) -> DataFrame:
    """Distinct places with their weight: ``x0.., w``.  Equal points get equal labels."""
    return points.groupBy(*[F.col(a).cast("double").alias(f"x{i}") for i, a in enumerate(axes)]).agg(F.count("*").alias("w"))


def xs(axes: tuple[str, ...]) -> list[str]:
    return [f"x{i}" for i in range(len(axes))]


def back(points: DataFrame, labelled: DataFrame, axes: tuple[str, ...]) -> DataFrame:
    """Joins labels of places (``x0.., label``) to the points."""
    cond = None
    for i, a in enumerate(axes):
        same = F.col(a).cast("double").eqNullSafe(F.col(f"x{i}"))
        cond = same if cond is None else cond & same
    return points.join(labelled.select(*xs(axes), "label"), cond, "left").drop(*xs(axes))


def collect_capped(points: DataFrame, axes: tuple[str, ...], method: str, cap: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and weights for a method of quadratic memory, or BaselineTooLarge."""
    rows = points.count()
    if rows > cap:
        raise BaselineTooLarge(method, rows, cap)
    pdf = places(points, axes).orderBy(*xs(axes)).toPandas()
    return pdf[xs(axes)].to_numpy(), pdf["w"].to_numpy()


def labels_frame(points: DataFrame, axes: tuple[str, ...], at: np.ndarray, labels: np.ndarray) -> DataFrame:
    rows = [(*map(float, p), int(v)) for p, v in zip(at, labels)]
    made = points.sparkSession.createDataFrame(rows, ", ".join(f"{x} double" for x in xs(axes)) + ", label bigint")
    return back(points, made, axes)


class Nearest:
    """Exact nearest centres by a grid over the first two axes, ring by ring.

    What lies beyond ``r`` rings is at least ``r`` sides away; points that a few rings do
    not settle meet, some of them at a time, all centres that may be nearest to any place of
    their box.  Ties go to the smaller number.
    """

    RINGS, TABLE, RUN, FEW, CHUNK = 4, 2_000_000, 64, 128, 256

    def __init__(self, centres: np.ndarray):
        self.centres = np.asarray(centres, float)
        self.flat = _two_axes(self.centres)
        self.low, self.side, self.shape = _grid(self.flat, len(self.flat))
        cell = np.floor((self.flat - self.low) / self.side).astype(np.int64)
        code = cell[:, 0] * self.shape[1] + cell[:, 1]
        self.order = np.argsort(code, kind="stable")
        self.starts = np.searchsorted(code[self.order], np.arange(self.shape[0] * self.shape[1] + 1))

    def _better(self, x, at, which, d2, best) -> None:
        new = ((x[at] - self.centres[which]) ** 2).sum(1)
        won = (new < d2[at]) | ((new == d2[at]) & (which < best[at]))
        d2[at[won]], best[at[won]] = new[won], which[won]

    def find(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number of the nearest centre, squared distance) of every point."""
        n = len(x)
        d2, best = np.full(n, np.inf), np.full(n, len(self.centres), np.int64)
        at = np.arange(n)
        home = np.floor(np.clip((_two_axes(x) - self.low) / self.side, -1e9, 1e9)).astype(np.int64) if n else np.zeros((0, 2), np.int64)
        for ring in range(self.RINGS if len(self.centres) > 32 else 0):
            for i in range(-ring, ring + 1):
                for j in range(-ring, ring + 1) if abs(i) == ring else (-ring, ring):
                    cx, cy = home[at, 0] + i, home[at, 1] + j
                    inside = (cx >= 0) & (cx < self.shape[0]) & (cy >= 0) & (cy < self.shape[1])
                    who = at[inside]
                    code = cx[inside] * self.shape[1] + cy[inside]
                    start, held, nth = self.starts[code], self.starts[code + 1] - self.starts[code], 0
                    while True:
                        more = held > nth
                        if not more.all():
                            who, start, held = who[more], start[more], held[more]
                        if not len(who):
                            break
                        self._better(x, who, self.order[start + nth], d2, best)
                        nth += 1
            at = at[d2[at] >= (ring * self.side * (1 - 1e-9)) ** 2]
            if not len(at):
                break
        chunk = self.CHUNK if len(self.centres) > self.CHUNK else max(1, len(at))
        for i in range(0, len(at), chunk):
            some = at[i : i + chunk]
            sub = self._facing(x[some].min(0), x[some].max(0)) if chunk == self.CHUNK else np.arange(len(self.centres))
            step = max(1, self.TABLE // max(1, len(sub)))
            for k in range(0, len(some), step):
                part = some[k : k + step]
                far = sum((x[part, c, None] - self.centres[None, sub, c]) ** 2 for c in range(x.shape[1]))
                best[part], d2[part] = sub[far.argmin(1)], far.min(1)
        return best, d2

    def _facing(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Numbers of the centres that may be nearest to some place of a box, in their order.

        None is farther from its middle than the nearest by over twice the half diagonal, or
        farther than that one from the corner that favours it most.
        """
        mid = (low + high) / 2
        d2 = ((self.centres - mid) ** 2).sum(1)
        first = self.centres[d2.argmin()]
        reach = (np.sqrt(d2.min()) + 2 * np.sqrt(((high - mid) ** 2).sum())) * (1 + 1e-9)
        sub = np.flatnonzero(~(d2 > reach**2))
        corner = np.where(self.centres[sub] > first, high, low)
        return sub[~(((corner - self.centres[sub]) ** 2).sum(1) * (1 - 1e-9) > ((corner - first) ** 2).sum(1))]

    def along(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What ``find`` returns, for points that mostly lie near the one before them.

        They are cut into runs, at long steps too.  A run in a box of half diagonal ``r``,
        whose middle has a centre at ``d``, meets only centres up to ``d + 2 r`` from the
        middle, without those that are farther than that centre from the whole box.  Runs
        that are left with many centres give their points to ``find``.
        """
        n, dim = x.shape
        if n < 2 or len(self.centres) <= 32:
            return self.find(x)
        axes = [np.ascontiguousarray(x[:, i]) for i in range(dim)]
        step = np.maximum.reduce([np.abs(np.diff(a)) for a in axes])
        cut = np.r_[True, step > 8 * step.mean()]
        cut[:: self.RUN] = True
        starts = np.flatnonzero(cut)
        held = np.diff(np.r_[starts, n])
        low, high = (np.stack([f.reduceat(a, starts) for a in axes], 1) for f in (np.minimum, np.maximum))
        mid = (low + high) / 2
        first, d2 = self.find(mid)
        reach = (np.sqrt(d2) + 2 * np.sqrt(((high - mid) ** 2).sum(1))) * (1 + 1e-9)
        pairs = []
        for run, met in self._within(mid, reach, low, high):
            # as in _facing, box by box
            at, other = self.centres[met], self.centres[first[run]]
            corner = np.where(at > other, high[run], low[run])
            near = ((corner - at) ** 2).sum(1) * (1 - 1e-9) <= ((corner - other) ** 2).sum(1)
            near &= np.bincount(run[near], minlength=len(starts))[run] <= self.FEW
            pairs.append((run[near], met[near]))
        run, met = (np.concatenate(p) for p in zip(*pairs))
        order = np.argsort(run * len(self.centres) + met)
        run, met = run[order], met[order]
        many = np.bincount(run, minlength=len(starts))
        nth = np.cumsum(many) - many
        best, d2 = np.zeros(n, np.int64), np.full(n, np.inf)
        for turn in range(int(many.max(initial=0))):
            which = np.flatnonzero(many > turn)
            c, size = met[nth[which] + turn], held[which]
            rows = slice(None) if len(which) == len(starts) else _spans(starts[which], size)
            new = sum((a[rows] - np.repeat(self.centres[c, i], size)) ** 2 for i, a in enumerate(axes))
            c = np.repeat(c, size)
            if turn:
                won = new < d2[rows]
                rows, c, new = rows[won] if isinstance(rows, np.ndarray) else won, c[won], new[won]
            best[rows], d2[rows] = c, new
        left = _spans(starts[many == 0], held[many == 0])
        if len(left):
            best[left], d2[left] = self.find(x[left])
        return best, d2

    def _within(self, mid: np.ndarray, reach: np.ndarray, low: np.ndarray, high: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(box, centre) of centres within reach of a box's middle; by the grid where few cells and centres are."""
        flat, most = _two_axes(mid), np.array(self.shape) - 1
        a, b = (np.clip(np.floor((flat + d * reach[:, None] - self.low) / self.side), 0, most) for d in (-1, 1))
        few = np.flatnonzero((b - a)[:, 0] < self.FEW)
        a, b = a[few].astype(np.int64), b[few].astype(np.int64)
        lines = b[:, 0] - a[:, 0] + 1
        place = np.repeat(np.arange(len(few)), lines)
        line = _spans(a[:, 0], lines) * self.shape[1]
        begin, end = self.starts[line + a[place, 1]], self.starts[line + b[place, 1] + 1]
        listed = np.bincount(place, end - begin, len(few)) <= self.FEW
        kept = listed[place]
        place, begin, size = few[place[kept]], begin[kept], (end - begin)[kept]
        place, met = np.repeat(place, size), self.order[_spans(begin, size)]
        near = ((mid[place] - self.centres[met]) ** 2).sum(1) <= reach[place] ** 2
        yield place[near], met[near]
        wide = np.setdiff1d(np.arange(len(mid)), few[listed])
        for i in range(0, len(wide), self.CHUNK):
            some = wide[i : i + self.CHUNK]
            sub = self._facing(low[some].min(0), high[some].max(0))
            step = max(1, self.TABLE // max(1, len(sub)))
            for k in range(0, len(some), step):
                part = some[k : k + step]
                d2 = sum((mid[part, c, None] - self.centres[None, sub, c]) ** 2 for c in range(mid.shape[1]))
                place, met = np.nonzero(d2 <= reach[part, None] ** 2)
                yield part[place], sub[met]


def _spans(starts: np.ndarray, held: np.ndarray) -> np.ndarray:
    """The numbers ``start .. start + held - 1`` of each span, one span after the other."""
    return np.repeat(starts - (np.cumsum(held) - held), held) + np.arange(held.sum())


def _two_axes(x: np.ndarray) -> np.ndarray:
    return x[:, :2] if x.shape[1] > 1 else np.column_stack([x, np.zeros(len(x))])


def _grid(flat: np.ndarray, cells: int) -> tuple[np.ndarray, float, tuple[int, int]]:
    """Least corner, side and number of cells by axis of a grid of some ``cells`` cells."""
    low, wide = flat.min(0), np.ptp(flat, axis=0)
    side = max(float(np.sqrt(wide[0] * wide[1] / cells)), float(wide.max()) / cells, 1e-300)
    return low, side, tuple(int(np.floor(w / side)) + 1 for w in wide)


def close_pairs(at: DataFrame, axes: tuple[str, ...], eps: float, carry: tuple[str, ...] = (), other: DataFrame | None = None) -> DataFrame:
    """All ordered pairs of places within ``eps``, each with itself as well.

    Cells of side ``2 eps`` and an equi-join with the cells that a partner's reach touches;
    then the exact distance.  Places are ``x..``, their partners ``y..``, of ``other`` if
    given; carried columns get ``y_``.
    """
    dim, side, reach = len(axes), 2 * eps, 1.0001 * eps
    celled = at.withColumns({f"c{i}": F.floor(F.col(f"x{i}") / side).cast("bigint") for i in range(dim)})
    around = (at if other is None else other).select(*[F.col(f"x{i}").alias(f"y{i}") for i in range(dim)], *[F.col(c).alias(f"y_{c}") for c in carry])
    for i in range(dim):
        first, last = (F.floor((F.col(f"y{i}") + d) / side).cast("bigint") for d in (-reach, reach))
        around = around.withColumn(f"c{i}", F.explode(F.sequence(first, last)))
    d2 = sum(((F.col(f"x{i}") - F.col(f"y{i}")) * (F.col(f"x{i}") - F.col(f"y{i}")) for i in range(1, dim)), (F.col("x0") - F.col("y0")) * (F.col("x0") - F.col("y0")))
    return celled.join(around, [f"c{i}" for i in range(dim)]).where(d2 <= eps * eps).withColumn("d2", d2).drop(*[f"c{i}" for i in range(dim)])


def number_roots(labelled: DataFrame, root: Column, axes: tuple[str, ...]) -> DataFrame:
    """Cluster numbers in the order of their roots; the window sees roots only."""
    rows = labelled.withColumn("_root", root)
    numbered = rows.select("_root").where("_root is not null").distinct().withColumn("label", (F.row_number().over(Window.orderBy("_root")) - 1).cast("bigint"))
    return rows.join(numbered, "_root", "left").select(*xs(axes), "label")
