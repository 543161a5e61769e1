"""The comparison, precision, speedup and memory experiments as tables of JSON lines.

    python experiments.py compare|precision|speedup|memory [--sf DIR] [--out FILE] [--runs N]

``speedup`` starts one session per number of cores, so it must be run on its own.
"""

from __future__ import annotations

import argparse
import json
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub import baselines as B
from gridhub.config import Neighborhood, TileParams
from gridhub.operators import metrics as M
from gridhub.operators import variants as V
from gridhub.operators.agglomerate import tile_clusters
from gridhub.operators.contract import count_tiles, significant
from gridhub.operators.sliced import slice_clusters
from gridhub.plans.staging import stage
from gridhub.sources.hubs import e7_grid, hub_grid, hub_points, replicas

AXES, PARAMS = ("x", "y"), TileParams(5, 4)


def start(cores: int) -> SparkSession:
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(cores)).config("spark.driver.memory", "10g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def tile_labels(points: DataFrame) -> DataFrame:
    grid = e7_grid("35")
    labelled = V.label_points(points, stage(tile_clusters(points, grid, PARAMS), "clusters"), grid)
    return labelled.withColumn("label", F.when(F.col("r_tx").isNotNull(), F.col("r_tx") * 1_000_000_000 + F.col("r_ty")))


METHODS: dict[str, Callable[[DataFrame, int], DataFrame]] = {
    "tiles_two_pass": lambda p, k: tile_labels(p), "mean_shift": lambda p, k: B.mean_shift(p, AXES, 1.0), "dbscan": lambda p, k: B.dbscan(p, AXES, 0.2, 5),
    "minibatch_kmeans": lambda p, k: B.minibatch_kmeans(p, AXES, k), "birch": lambda p, k: B.birch(p, AXES, 0.3, 50, k), "gaussian_mixture": lambda p, k: B.gaussian_mixture(p, AXES, k),
    "ward": lambda p, k: B.ward(p, AXES, k), "average_linkage": lambda p, k: B.linkage_by_parts(p, AXES, k, "average", 0.4), "complete_linkage": lambda p, k: B.linkage_by_parts(p, AXES, k, "complete", 0.4), "spectral": lambda p, k: B.spectral(p, AXES, k), "affinity": lambda p, k: B.affinity_propagation(p, AXES),
}


def compare(spark: SparkSession, folder: str, runs: int, tell: Callable[[dict], None]) -> None:
    """All methods on one size: share of hubs matched, time, silhouette."""
    points = stage(hub_points(spark, folder).select("hub", "lon_e7", "lat_e7", (F.col("lon_e7") / 1e4).alias("x"), (F.col("lat_e7") / 1e4).alias("y")), "points")
    hubs = points.select("hub").distinct().count()
    for name, run in METHODS.items():
        try:
            took = M.timed(lambda r=run: r(points, hubs), runs)
            labelled = stage(run(points, hubs).select("hub", "x", "y", "label"), "found")
            tell({"experiment": "compare", "method": name, "hubs": hubs, "matched": M.matched_ratio(labelled, "hub", ["label"]).first()["percent"], "silhouette": M.silhouette(labelled, AXES, "label").first()["silhouette"], "silhouette_sq": M.silhouette_fast(labelled, AXES, "label").first()["silhouette"], **took})
        except B.BaselineTooLarge as e:
            tell({"experiment": "compare", "method": name, "hubs": hubs, "refused": str(e)})
    began = time.perf_counter()
    side = 400
    found = B.clique(points, AXES, side, 5 / points.count())
    tell({"experiment": "compare", "method": "clique", "hubs": hubs, "clusters": found.select("r_tx", "r_ty").distinct().count(), "mean": time.perf_counter() - began})


def precision(spark: SparkSession, folder: str, runs: int, tell: Callable[[dict], None]) -> None:
    """Base and retaining form at four precisions and two sizes."""
    base = stage(hub_points(spark, folder).select("hub", "lon_e7", "lat_e7"), "points")
    for copies in (1, 10):
        points = base if copies == 1 else stage(replicas(base, copies), "points")
        hubs = points.select("hub").distinct().count()
        for level in ("3", "35", "4", "5"):
            grid = e7_grid(level)
            clusters = stage(tile_clusters(points, grid, PARAMS), "clusters")
            row = {"experiment": "precision", "p": level, "hubs": hubs, "found": M.found_ratio(clusters, hubs).first()["percent"], "matched": M.matched_ratio(V.label_points(points, clusters, grid)).first()["percent"]}
            tell(row | {"form": "base"} | M.timed(lambda p=points, g=grid: tile_clusters(p, g, PARAMS), runs))
            tell(row | {"form": "retaining"} | M.timed(lambda p=points, g=grid: V.tile_clusters_points(p, g, PARAMS), runs))


def speedup(folder: str, runs: int, tell: Callable[[dict], None]) -> None:
    """Sliced form on 1, 2, 4 and 8 cores, by phase."""
    times: dict[int, float] = {}
    for cores in (1, 2, 4, 8):
        spark = start(cores)
        points = stage(replicas(hub_points(spark, folder).select("hub", "lon_e7", "lat_e7"), 50), "points")
        run = lambda: slice_clusters(significant(count_tiles(points, e7_grid("35")), 5), Neighborhood(), cores, mu=4)  # noqa: E731, B023
        run().write.format("noop").mode("overwrite").save()
        took = M.timed(run, runs)
        sig = stage(significant(count_tiles(points, e7_grid("35")), 5), "sig")
        parts = M.phase_times([("contract", lambda: significant(count_tiles(points, e7_grid("35")), 5)), ("agglomerate", lambda: slice_clusters(sig, Neighborhood(), cores, mu=4))])  # noqa: B023
        times[cores] = took["mean"]
        tell({"experiment": "speedup", "cores": cores, "points": points.count(), **took, **parts, **M.speedup(times)[cores]})
        spark.stop()


def memory(spark: SparkSession, folder: str, runs: int, tell: Callable[[dict], None]) -> None:
    """How far each method gets on generated hubs, and how time grows."""
    for name, run in METHODS.items():
        def grow(hubs: int, run=run) -> DataFrame:
            made = stage(hub_grid(spark, hubs, 500).select("hub", "lon_e7", "lat_e7", (F.col("lon_e7") / 1e4).alias("x"), (F.col("lat_e7") / 1e4).alias("y")), "grown")
            return run(made, hubs)
        rows = M.size_ladder(grow, [10, 100, 1000], 120)
        good = [r for r in rows if r["ok"]]
        slope = M.scaling_slope([r["size"] for r in good], [r["seconds"] for r in good]) if len(good) > 1 else None
        tell({"experiment": "memory", "method": name, "ladder": rows, "slope": slope})


def main() -> None:
    ask = argparse.ArgumentParser()
    ask.add_argument("what", choices=["compare", "precision", "speedup", "memory"])
    ask.add_argument("--sf", default="/root/testdata/sf0.01")
    ask.add_argument("--out")
    ask.add_argument("--runs", type=int, default=3)
    ask.add_argument("--cores", type=int, default=8)
    given = ask.parse_args()

    def tell(row: dict) -> None:
        line = json.dumps(row)
        print(line, flush=True)
        if given.out:
            with open(given.out, "a") as f:
                f.write(line + "\n")

    if given.what == "speedup":
        return speedup(given.sf, given.runs, tell)
    run = {"compare": compare, "precision": precision, "memory": memory}[given.what]
    run(start(given.cores), given.sf, given.runs, tell)


if __name__ == "__main__":
    main()
