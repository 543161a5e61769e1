"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Times are means over RUNS runs into the noop sink after one warm-up run.  ``base_*`` is
the counting form at four precisions, ``retain_*`` keeps points, ``label`` is the two-pass
labeller, ``sliced_*`` the sliced form; ``*_60m`` runs on shifted copies of the points, a
size at which the engine's fixed costs no longer matter; ``*_60k`` are baselines on a tenth
of the hubs.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from gridhub import baselines
from gridhub.config import Neighborhood, TileParams
from gridhub.operators import metrics, variants
from gridhub.operators.agglomerate import keep_clusters, agglomerate, tile_clusters
from gridhub.operators.contract import count_tiles, significant
from gridhub.operators.sliced import slice_clusters
from gridhub.plans.staging import stage
from gridhub.sources.hubs import e7_grid, hub_points, replicas

RUNS = int(os.environ.get("BENCH_RUNS", "2"))
PARAMS = TileParams(5, 4)


def session() -> SparkSession:
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    folder = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session()
    points = stage(hub_points(spark, folder).select("hub", "lon_e7", "lat_e7"), "points")
    rows = points.count()
    large = stage(replicas(points, 100), "large")
    runs = {}
    for level in ("3", "35", "4", "5"):
        runs[f"base_p{level}"] = lambda v=level: tile_clusters(points, e7_grid(v), PARAMS)
        runs[f"retain_p{level}"] = lambda v=level: variants.tile_clusters_points(points, e7_grid(v), PARAMS)
    runs["label_p35"] = lambda: variants.label_points(points, tile_clusters(points, e7_grid("35"), PARAMS), e7_grid("35"))
    runs["sliced8_p35"] = lambda: slice_clusters(significant(count_tiles(points, e7_grid("35")), 5), Neighborhood(), 8, mu=4)
    runs["rescue_p4"] = lambda: keep_clusters(agglomerate(variants.rescue_windows(count_tiles(points, e7_grid("4")), 5)), 4)
    runs["matched_p35"] = lambda: metrics.matched_ratio(variants.label_points(points, tile_clusters(points, e7_grid("35"), PARAMS), e7_grid("35")))
    for level in ("3", "35", "4"):
        runs[f"counts_p{level}_60m"] = lambda v=level: significant(count_tiles(large, e7_grid(v)), 5)
    runs["base_p35_60m"] = lambda: tile_clusters(large, e7_grid("35"), PARAMS)
    runs["sliced8_p35_60m"] = lambda: slice_clusters(significant(count_tiles(large, e7_grid("35")), 5), Neighborhood(), 8, mu=4)
    runs["retain_p35_60m"] = lambda: variants.tile_clusters_points(large, e7_grid("35"), PARAMS)
    small = stage(points.where(F.col("hub") <= 100).select("hub", (F.col("lon_e7") / 1e4).alias("x"), (F.col("lat_e7") / 1e4).alias("y")), "small")
    axes = ("x", "y")
    runs["dbscan_60k"] = lambda: baselines.dbscan(small, axes, 0.2, 5)
    runs["minibatch_kmeans_60k"] = lambda: baselines.minibatch_kmeans(small, axes, 100)
    runs["average_linkage_60k"] = lambda: baselines.linkage_by_parts(small, axes, 100, "average", 0.4)
    runs["mean_shift_60k"] = lambda: baselines.mean_shift(small, axes, 1.0)
    once = {"average_linkage_60k", "mean_shift_60k"}  # slow methods are run once, unwarmed
    took = {}
    for name, run in runs.items():
        turns = 1 if name in once else RUNS
        if name not in once:
            run().write.format("noop").mode("overwrite").save()
        began = time.perf_counter()
        for _ in range(turns):
            run().write.format("noop").mode("overwrite").save()
        took[name] = round((time.perf_counter() - began) / turns, 3)
    found = {v: variants.label_points(points, tile_clusters(points, e7_grid(v), PARAMS), e7_grid(v)) for v in ("3", "35", "4", "5")}
    percent = {v: metrics.matched_ratio(df).first()["percent"] for v, df in found.items()}
    many = large.agg(F.count("*")).first()[0]
    print(json.dumps({
        "metric": "grid_clustering_total_sec", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": folder.rstrip("/").rsplit("/sf", 1)[-1],
        "points": rows, "points_large": many, "large_points_per_sec": round(many / took["base_p35_60m"]), "matched_percent": percent, "cpus": os.environ.get("BENCH_CPUS", "8"), "runs": RUNS,
    }))
    spark.stop()


if __name__ == "__main__":
    main()
