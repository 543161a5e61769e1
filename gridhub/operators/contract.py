"""Contraction: points per tile, and the tiles that have enough of them."""

from __future__ import annotations

from collections.abc import Iterable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub.config import Grid
from gridhub.operators.project import with_tile
from gridhub.plans.staging import stage


def count_tiles(points: DataFrame, grid: Grid, weight: str | None = None) -> DataFrame:
    """``tile, n``: one scan of the axis columns, partial counts before the exchange."""
    n = F.count("*") if weight is None else F.sum(weight)
    return with_tile(points, grid).groupBy(*grid.keys).agg(n.cast("bigint").alias("n"))


def count_distinct_points(points: DataFrame, grid: Grid) -> DataFrame:
    """``tile, n`` where equal points count once."""
    return count_tiles(points.select(*grid.axes).distinct(), grid)


def significant(counts: DataFrame, tau: int) -> DataFrame:
    return counts.where(F.col("n") >= tau)


def merge_counts(*parts: DataFrame) -> DataFrame:
    """Adds tile counts; commutative and associative, so chunks may come in any order."""
    keys = [c for c in parts[0].columns if c != "n"]
    return reduce(DataFrame.unionByName, parts).groupBy(*keys).agg(F.sum("n").cast("bigint").alias("n"))


def count_chunks(chunks: Iterable[DataFrame], grid: Grid) -> DataFrame:
    """Counts of many inputs; points of a chunk are never held."""
    return merge_counts(*(count_tiles(c, grid) for c in chunks))


def tree_merge(parts: list[DataFrame], fan_in: int = 8) -> DataFrame:
    """``merge_counts`` level by level, staged, for very many chunks."""
    while len(parts) > 1:
        parts = [stage(merge_counts(*parts[i : i + fan_in]), "merge") for i in range(0, len(parts), fan_in)]
    return parts[0]


def tile_sketch(points: DataFrame, grid: Grid) -> DataFrame:
    """Sizing without a run: points, occupied tiles (HyperLogLog) and spread per axis."""
    tiled = with_tile(points, grid)
    return tiled.agg(F.count("*").alias("points"), F.approx_count_distinct(F.struct(*grid.keys), 0.02).alias("tiles"), *[F.min(k).alias(f"{k}_min") for k in grid.keys], *[F.max(k).alias(f"{k}_max") for k in grid.keys])


def tau_candidates(counts: DataFrame, shares: tuple[float, ...] = (0.5, 0.9, 0.99)) -> DataFrame:
    """Quantiles of the count per tile, to choose tau by."""
    return counts.agg(F.percentile_approx("n", list(shares), 10000).alias("q")).select(*[F.col("q")[i].alias(f"p{int(s * 1000)}") for i, s in enumerate(shares)])


class CountStore:
    """Tile counts kept as Parquet by coarse tile; later batches are added to what is there.

    Every ``add`` writes a new generation beside the old one and then moves a pointer file,
    so a failed write leaves the store as it was.
    """

    def __init__(self, spark: SparkSession, path: str, grid: Grid, coarse: int = 1024):
        self.spark, self.path, self.grid, self.coarse = spark, path.rstrip("/"), grid, coarse

    def _pointer(self):
        jvm = self.spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(f"{self.path}/CURRENT")
        return at, at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def generation(self) -> int:
        at, fs = self._pointer()
        if not fs.exists(at):
            return 0
        return int(self.spark.read.text(str(at.toString())).first()[0])

    def read(self) -> DataFrame:
        now = self.generation()
        if not now:
            return self.spark.createDataFrame([], ", ".join(f"{k} bigint" for k in self.grid.keys) + ", n bigint")
        return self.spark.read.parquet(f"{self.path}/g{now}").select(*self.grid.keys, "n")

    def add(self, points: DataFrame) -> None:
        fresh, now = count_tiles(points, self.grid), self.generation()
        both = merge_counts(self.read(), fresh) if now else fresh
        coarse = F.floor(F.col(self.grid.keys[0]) / self.coarse).cast("bigint")
        both.withColumn("coarse", coarse).write.partitionBy("coarse").parquet(f"{self.path}/g{now + 1}")
        at, fs = self._pointer()
        out = fs.create(at, True)
        out.write(bytearray(str(now + 1).encode()))
        out.close()
