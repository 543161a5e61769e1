"""Relational work around tiles: sweeps, moving windows, rankings, sketches, comparisons."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridhub.operators.neighbors import tile_keys


def tau_sweep(counts: DataFrame, taus: list[int]) -> DataFrame:
    """Significant tiles and points for many thresholds in one pass over the counts.

    The thresholds are a literal array of the plan, exploded beside each tile.
    """
    rows = counts.withColumn("tau", F.explode(F.array(*[F.lit(t) for t in taus]))).where(F.col("n") >= F.col("tau"))
    return rows.groupBy("tau").agg(F.count("*").alias("tiles"), F.sum("n").cast("bigint").alias("points"))


def parameter_grid(spark: SparkSession, counts: DataFrame, taus: list[int], factors: list[int]) -> DataFrame:
    """Thresholds by coarsening factors: a broadcast cross join with a table of parameters."""
    grid = spark.createDataFrame([(t, f) for t in taus for f in factors], "tau int, factor int")
    keys = tile_keys(counts)
    coarse = counts.crossJoin(F.broadcast(grid)).groupBy("tau", "factor", *[F.floor(F.col(k) / F.col("factor")).cast("bigint").alias(k) for k in keys]).agg(F.sum("n").alias("n"))
    return coarse.where(F.col("n") >= F.col("tau")).groupBy("tau", "factor").agg(F.count("*").alias("tiles"), F.sum("n").cast("bigint").alias("points"))


def moving_counts(daily: DataFrame, days: int, day: str = "day") -> DataFrame:
    """Per tile, the sum over a range frame of ``days`` days up to each day that has rows."""
    frame = Window.partitionBy(*tile_keys(daily)).orderBy(day).rangeBetween(-(days - 1), 0)
    return daily.withColumn("moving", F.sum("n").over(frame).cast("bigint"))


def rank_tiles(clusters: DataFrame) -> DataFrame:
    """Places of tiles inside their cluster by count, in every usual way of ranking."""
    roots = [f"r_{k}" for k in tile_keys(clusters)]
    by_count = Window.partitionBy(*roots).orderBy(F.desc("n"))
    strict = Window.partitionBy(*roots).orderBy(F.desc("n"), *tile_keys(clusters))
    return clusters.select(
        *roots, *tile_keys(clusters), "n", F.rank().over(by_count).alias("rank"), F.dense_rank().over(by_count).alias("dense_rank"),
        F.row_number().over(strict).alias("row_number"), F.ntile(4).over(strict).alias("quarter"), F.round(F.percent_rank().over(by_count), 6).alias("percent_rank"),
        F.first("n").over(strict).alias("top"), F.nth_value("n", 2).over(strict.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second"),
    )


def compare_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """Tiles whose counts differ between two runs: a full outer join."""
    keys = list(tile_keys(a))
    both = a.withColumnRenamed("n", "n_a").join(b.withColumnRenamed("n", "n_b"), keys, "full")
    return both.select(*keys, F.coalesce("n_a", F.lit(0)).alias("n_a"), F.coalesce("n_b", F.lit(0)).alias("n_b")).where("n_a <> n_b")


def noise_tiles(counts: DataFrame, clusters: DataFrame) -> DataFrame:
    """Occupied tiles outside all clusters: an anti join."""
    keys = list(tile_keys(counts))
    return counts.join(clusters.select(*keys), keys, "left_anti")


def densest(counts: DataFrame, many: int) -> DataFrame:
    """The densest tiles, ties by place: a top-k without a full sort."""
    return counts.orderBy(F.desc("n"), *tile_keys(counts)).limit(many)


def column_profile(counts: DataFrame) -> DataFrame:
    """Count per column of tiles and its running total, which balanced slices cut."""
    first = tile_keys(counts)[0]
    columns = counts.groupBy(first).agg(F.sum("n").cast("bigint").alias("n"), F.count("*").alias("tiles"))
    return columns.withColumn("upto", F.sum("n").over(Window.orderBy(first).rowsBetween(Window.unboundedPreceding, 0)).cast("bigint"))


def vehicle_sketches(points: DataFrame, group: list[str], vehicle: str) -> DataFrame:
    """Vehicles per group by a mergeable sketch, and all vehicles by their union."""
    per = points.groupBy(*group).agg(F.hll_sketch_agg(vehicle).alias("sketch"))
    rows = per.select(*group, F.hll_sketch_estimate("sketch").alias("vehicles"))
    whole = per.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("vehicles"))
    return rows.unionByName(whole.select(*[F.lit(None).cast(dict(rows.dtypes)[g]).alias(g) for g in group], "vehicles"))


def heavy_tiles(tiled: DataFrame, keys: list[str], share: float = 0.001) -> DataFrame:
    """Tiles that may hold ``share`` of all rows, from a count-min sketch's size, exactly.

    The sketch bounds how many there can be; the counting itself stays a grouped count.
    """
    total = tiled.agg(F.count("*").alias("rows"), F.length(F.count_min_sketch(F.xxhash64(*keys), F.lit(0.001), F.lit(0.99), F.lit(7))).alias("sketch_bytes"))
    counted = tiled.groupBy(*keys).agg(F.count("*").alias("n"))
    return counted.crossJoin(F.broadcast(total)).where(F.col("n") >= F.col("rows") * share)


def by_type_and_day(events: DataFrame) -> DataFrame:
    """Counts by event type, by day, and overall, as grouping sets."""
    events.createOrReplaceTempView("_typed_events")
    return events.sparkSession.sql("""
        SELECT event_type, cast(ts AS date) AS day, cast(grouping_id(event_type, cast(ts AS date)) AS bigint) AS level, count(*) AS n
        FROM _typed_events GROUP BY GROUPING SETS ((event_type), (cast(ts AS date)), ())""")


def long_profile(wide: DataFrame, keys: list[str], values: list[str]) -> DataFrame:
    """One row per key and column of a pivoted profile."""
    return wide.unpivot(keys, values, "part", "visits")
