"""Accuracy and cost measures."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridhub.plans.staging import stage

#: Cluster summaries that may go to every task, some 60 bytes each.
MAX_CLUSTERS = 2_000_000


def found_ratio(clusters: DataFrame, truth: int, roots: list[str] | None = None) -> DataFrame:
    """Clusters found over clusters generated, in percent; splits can pass 100."""
    roots = roots or [c for c in clusters.columns if c.startswith("r_")]
    return clusters.select(*roots).distinct().agg(F.count("*").alias("found")).withColumn("percent", F.round(F.col("found") * 100.0 / F.lit(truth), 6))


def matched_ratio(labelled: DataFrame, truth: str = "hub", roots: list[str] | None = None) -> DataFrame:
    """Hubs met by exactly one cluster that meets only that hub."""
    roots = roots or [c for c in labelled.columns if c.startswith("r_")]
    hubs = labelled.select(truth).where(F.col(truth) >= 0).distinct().agg(F.count("*").alias("hubs"))
    pairs = labelled.where(F.col(roots[0]).isNotNull() & (F.col(truth) >= 0)).select(F.col(truth).alias("h"), F.struct(*roots).alias("c")).distinct()
    one_hub = pairs.groupBy("c").agg(F.count("*").alias("k"), F.min("h").alias("h")).where("k = 1")
    one_cluster = pairs.groupBy("h").agg(F.count("*").alias("k")).where("k = 1").select("h")
    good = one_hub.join(one_cluster, "h", "left_semi").agg(F.count("*").alias("matched"))
    return good.crossJoin(hubs).withColumn("percent", F.round(F.col("matched") * 100.0 / F.nullif(F.col("hubs"), F.lit(0)), 6))


#: Places of a block; two blocks meet in one matrix of distances.
BLOCK = 1024


def _cluster_stats(rows: DataFrame, axes: tuple[str, ...]) -> DataFrame:
    """Per cluster ``l``: rows ``m``, centre ``c0..``, mean square distance ``v`` and reach ``r`` from it."""
    dim = len(axes)
    centres = rows.groupBy("l").agg(F.sum("w").alias("m"), *[(F.sum(F.col(f"x{i}") * F.col("w")) / F.sum("w")).alias(f"c{i}") for i in range(dim)])
    d2 = sum((F.pow(F.col(f"x{i}") - F.col(f"c{i}"), 2) for i in range(1, dim)), F.pow(F.col("x0") - F.col("c0"), 2))
    keys = ["l", "m", *[f"c{i}" for i in range(dim)]]
    return rows.join(centres, "l").groupBy(*keys).agg((F.sum(d2 * F.col("w")) / F.first("m")).alias("v"), F.sqrt(F.max(d2)).alias("r"))


def near_clusters(stats: DataFrame, dim: int, squared: bool) -> DataFrame:
    """``l, k``: the clusters k that can be nearest in mean distance to some point of l.

    A point of l is at most ``r`` from its centre.  The mean distance to a cluster is at
    least the distance to its centre and at most the root of the mean square, which adds
    ``v``; whatever stays above the least upper bound is out.  The summaries, a row a
    cluster, go to every task once their number is checked.
    """
    many = stats.count()
    if many > MAX_CLUSTERS:
        raise ValueError(f"{many} clusters; summaries of {MAX_CLUSTERS} at most are compared")
    names = [f"c{i}" for i in range(dim)]
    table = stats.select("l", *names, "v").toArrow()
    sent = stats.sparkSession.sparkContext.broadcast((table["l"].combine_chunks(), np.stack([table[c].to_numpy() for c in names], 1), table["v"].to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels, centre, spread = sent.value
        for batch in batches:
            mine, at, reach = batch.column("l"), np.stack([batch.column(c).to_numpy() for c in names], 1), batch.column("r").to_numpy()
            for i in range(batch.num_rows):
                far = np.sqrt(((centre - at[i]) ** 2).sum(1))
                low, high = np.maximum(far - reach[i], 0) ** 2, (far + reach[i]) ** 2 + spread
                if squared:
                    low = low + spread
                other = np.ones(len(far), bool)
                other[labels.index(mine[i]).as_py()] = False
                if other.any():
                    k = np.flatnonzero(other & (low <= high[other].min() * (1 + 1e-9)))
                    yield pa.RecordBatch.from_pydict({"l": pa.array([mine[i].as_py()] * len(k), mine.type), "k": labels.take(pa.array(k))})

    kind = dict(stats.dtypes)["l"]
    return stats.select("l", *names, "r").mapInArrow(run, f"l {kind}, k {kind}")


def _label_rows(labelled: DataFrame, axes: tuple[str, ...], label: str) -> DataFrame:
    """Distinct places of labelled rows with their weight: ``l, x0.., w``."""
    rows = labelled.where(F.col(label).isNotNull()).select(F.col(label).alias("l"), *[F.col(a).cast("double").alias(f"x{i}") for i, a in enumerate(axes)])
    return stage(rows.groupBy(*rows.columns).agg(F.count("*").alias("w")), "places")


def silhouette_fast(labelled: DataFrame, axes: tuple[str, ...], label: str) -> DataFrame:
    """Mean silhouette on squared Euclidean distance over all rows.

    Mean squared distances to a cluster follow from its count, centre and mean square, and
    a row is compared only with its own cluster and those that ``near_clusters`` leaves.
    Rows of a single-point cluster count as 0.
    """
    dim, rows = len(axes), _label_rows(labelled, axes, label)
    stats = stage(_cluster_stats(rows, axes), "stats")
    pairs = near_clusters(stats, dim, True).unionByName(stats.select("l", F.col("l").alias("k")))
    other = stats.select(F.col("l").alias("k"), "m", "v", *[f"c{i}" for i in range(dim)])
    d2 = sum((F.pow(F.col(f"x{i}") - F.col(f"c{i}"), 2) for i in range(1, dim)), F.pow(F.col("x0") - F.col("c0"), 2))
    met = rows.join(stage(pairs.join(other, "k"), "near"), "l").withColumn("d", d2 + F.col("v"))
    place = ["l", *[f"x{i}" for i in range(dim)], "w"]
    own = F.max(F.when((F.col("k") == F.col("l")) & (F.col("m") > 1), F.col("d") * F.col("m") / (F.col("m") - 1)))
    return _mean_silhouette(met.groupBy(*place).agg(own.alias("a"), F.min(F.when(F.col("k") != F.col("l"), F.col("d"))).alias("b")))


def silhouette(labelled: DataFrame, axes: tuple[str, ...], label: str) -> DataFrame:
    """Mean silhouette on Euclidean distance over all rows, exact.

    Every place is compared with all places of its own cluster and of those that
    ``near_clusters`` leaves, block by block, so that no cluster has to fit a task.
    """
    dim, rows = len(axes), _label_rows(labelled, axes, label)
    stats = stage(_cluster_stats(rows, axes), "stats")
    pairs = near_clusters(stats, dim, False).unionByName(stats.select("l", F.col("l").alias("k")))
    names = [f"x{i}" for i in range(dim)]
    sizes = rows.groupBy("l").agg(F.ceil(F.count("*") / BLOCK).alias("parts"))
    dealt = rows.join(sizes, "l").withColumn("part", F.pmod(F.xxhash64(*names), F.col("parts")))
    blocks = stage(dealt.groupBy("l", "part").agg(F.collect_list(F.struct(*names, "w")).alias("at")), "blocks")
    met = blocks.join(stage(pairs, "near"), "l").join(blocks.select(F.col("l").alias("k"), F.col("part").alias("other_part"), F.col("at").alias("other")), "k")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                one, other = batch.column("at")[i].values, batch.column("other")[i].values
                x, y = (np.stack([side.field(n).to_numpy() for n in names], 1) for side in (one, other))
                weight = other.field("w").to_numpy().astype(float)
                total = np.sqrt(((x[:, None] - y[None]) ** 2).sum(2)) @ weight
                flat = {n: x[:, j] for j, n in enumerate(names)} | {"w": one.field("w").to_numpy(), "total": total, "held": np.full(len(x), int(weight.sum()))}
                ends = {c: pa.array([batch.column(c)[i].as_py()] * len(x), batch.column(c).type) for c in ("l", "k")}
                yield pa.RecordBatch.from_pydict(ends | {c: pa.array(v) for c, v in flat.items()})

    kind = dict(stats.dtypes)["l"]
    schema = f"l {kind}, k {kind}, " + ", ".join(f"{n} double" for n in names) + ", w long, total double, held long"
    sums = met.select("l", "k", "at", "other").mapInArrow(run, schema).groupBy("l", "w", *names, "k").agg(F.sum("total").alias("total"), F.sum("held").alias("m"))
    own = F.max(F.when((F.col("k") == F.col("l")) & (F.col("m") > 1), F.col("total") / (F.col("m") - 1)))
    return _mean_silhouette(sums.groupBy("l", "w", *names).agg(own.alias("a"), F.min(F.when(F.col("k") != F.col("l"), F.col("total") / F.col("m"))).alias("b")))


def _mean_silhouette(per: DataFrame) -> DataFrame:
    value = F.when(F.col("a").isNull() | F.col("b").isNull() | (F.greatest("a", "b") == 0), F.lit(0.0)).otherwise((F.col("b") - F.col("a")) / F.greatest("a", "b"))
    return per.agg(F.round(F.sum(value * F.col("w")) / F.sum("w"), 6).alias("silhouette"), F.sum("w").cast("bigint").alias("points"))


def pair_scores(labelled: DataFrame, truth: str, label: str) -> DataFrame:
    """Adjusted Rand index and purity of a labelling against the truth, by contingency."""
    cells = labelled.where(F.col(truth).isNotNull() & F.col(label).isNotNull()).groupBy(F.col(truth).alias("t"), F.col(label).alias("l")).agg(F.count("*").alias("n"))
    two = lambda c: F.sum(c.cast("double") * (c - 1) / 2)
    by_t = cells.groupBy("t").agg(F.sum("n").alias("n")).agg(two(F.col("n")).alias("st"))
    by_l = cells.groupBy("l").agg(F.sum("n").alias("n"), F.max("n").alias("top")).agg(two(F.col("n")).alias("sl"), F.sum("top").alias("top"))
    base = cells.agg(two(F.col("n")).alias("s"), F.sum("n").alias("n")).crossJoin(by_t).crossJoin(by_l)
    all_pairs = F.col("n").cast("double") * (F.col("n") - 1) / 2
    chance = F.col("st") * F.col("sl") / all_pairs
    return base.select(F.round((F.col("s") - chance) / ((F.col("st") + F.col("sl")) / 2 - chance), 6).alias("ari"), F.round(F.col("top") / F.col("n"), 6).alias("purity"), F.col("n").cast("bigint").alias("points"))


def same_partition(a: DataFrame, b: DataFrame) -> bool:
    """Whether two clusterings have the same (root, tile) rows."""
    cols = sorted(c for c in a.columns if c.startswith(("r_", "t")))
    a, b = a.select(*cols), b.select(*cols)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Jaccard index of every pair of clusters that share a tile."""
    keys = [c for c in a.columns if c.startswith("t")]
    left = a.select(F.struct(*[c for c in a.columns if c.startswith("r_")]).alias("a"), *keys)
    right = b.select(F.struct(*[c for c in b.columns if c.startswith("r_")]).alias("b"), *keys)
    both = left.join(right, keys).groupBy("a", "b").agg(F.count("*").alias("shared"))
    sized = both.join(left.groupBy("a").agg(F.count("*").alias("na")), "a").join(right.groupBy("b").agg(F.count("*").alias("nb")), "b")
    return sized.withColumn("jaccard", F.col("shared") / (F.col("na") + F.col("nb") - F.col("shared")))


def timed(run: Callable[[], DataFrame], runs: int = 5) -> dict[str, float]:
    """Wall time of a query into the noop sink: mean and standard deviation."""
    took = []
    for _ in range(runs):
        began = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - began)
    return {"mean": statistics.mean(took), "sd": statistics.stdev(took) if runs > 1 else 0.0, "runs": runs}


def phase_times(phases: Iterable[tuple[str, Callable[[], DataFrame]]]) -> dict[str, float]:
    """Wall time of phases that each end in a staged table."""
    from gridhub.plans.staging import stage

    out = {}
    for name, run in phases:
        began = time.perf_counter()
        stage(run(), name)
        out[name] = time.perf_counter() - began
    return out


def speedup(times: dict[int, float]) -> dict[int, dict[str, float]]:
    """Speedup and efficiency by number of cores, against one core."""
    one = times[1]
    return {c: {"speedup": one / t, "efficiency": one / t / c} for c, t in times.items()}


def ratio(a: float, b: float) -> float:
    return a / b


def scaling_slope(sizes: list[int], seconds: list[float]) -> float:
    """Slope of log time against log size by least squares."""
    x, y = [math.log(s) for s in sizes], [math.log(t) for t in seconds]
    mx, my = statistics.mean(x), statistics.mean(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y)) / sum((a - mx) ** 2 for a in x)


def scaling_slope_sql(runs: DataFrame) -> DataFrame:
    """The same from a table of ``size, seconds``."""
    return runs.agg(F.regr_slope(F.log("seconds"), F.log("size")).alias("slope"))


def size_ladder(run: Callable[[int], DataFrame], sizes: list[int], limit_s: float) -> list[dict]:
    """Grow the input until a run fails or takes longer than the limit."""
    out = []
    for n in sizes:
        began = time.perf_counter()
        try:
            run(n).write.format("noop").mode("overwrite").save()
        except Exception as e:  # a method that refuses its input is what the ladder looks for
            out.append({"size": n, "ok": False, "why": type(e).__name__})
            break
        took = time.perf_counter() - began
        out.append({"size": n, "ok": True, "seconds": took})
        if took > limit_s:
            break
    return out


def memory_report(counts: DataFrame) -> DataFrame:
    """Rows that the method holds: occupied tiles and the bytes of their keys and counts."""
    keys = len([c for c in counts.columns if c != "n"])
    return counts.agg(F.count("*").alias("tiles"), (F.count("*") * (8 * (keys + 1))).alias("bytes"), F.sum("n").cast("bigint").alias("points"))


def noise_share(labelled: DataFrame, root: Column) -> DataFrame:
    return labelled.agg(F.count("*").alias("points"), F.count_if(root.isNull()).alias("noise"), F.round(F.count_if(root.isNull()) / F.count("*"), 6).alias("share"))
