"""Agglomeration: significant tiles to clusters, by engines that give the same rows.

A cluster is named by its lexicographically least tile, in columns ``r_<key>``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridhub.config import Grid, Neighborhood, TileParams
from gridhub.operators.components import star_components
from gridhub.operators.contract import count_tiles, significant
from gridhub.operators.neighbors import tile_edges, tile_keys
from gridhub.operators.unionfind import tile_components
from gridhub.plans.staging import release, stage

#: Tiles up to which one task (here: the driver) solves the whole graph.
DRIVER_TILES = 200_000
#: Estimated bytes of a plan up to which its tiles are asked for at once, unstaged; a guess
#: that proves wrong costs one more run of the plan.
SMALL_INPUT = 2 << 30
#: Spark's bound of a recursion's rows.
RECURSION_ROWS = "spark.sql.cteRecursionRowLimit"
ENGINES = ("auto", "driver", "propagate", "star", "blocks", "recursive")


def _named(sig: DataFrame, roots: DataFrame) -> DataFrame:
    """Joins (node, root) structs to the tiles; a tile without an edge is its own root."""
    keys = tile_keys(sig)
    flat = roots.select(*[F.col(f"node.{k}").alias(k) for k in keys], *[F.col(f"root.{k}").alias(f"r_{k}") for k in keys])
    joined = sig.join(flat, list(keys), "left")
    return joined.select(*[F.coalesce(f"r_{k}", k).alias(f"r_{k}") for k in keys], *sig.columns)


def _result_schema(sig: DataFrame) -> str:
    return ", ".join([f"r_{k} bigint" for k in tile_keys(sig)] + [f"`{f.name}` {f.dataType.simpleString()}" for f in sig.schema])


def _label_table(table: pa.Table, keys: tuple[str, ...], near: Neighborhood) -> pa.Table:
    tiles = np.stack([table[k].to_numpy() for k in keys], 1) if table.num_rows else np.zeros((0, len(keys)), np.int64)
    order = np.lexsort(tiles.T[::-1])
    sorted_tiles = tiles[order]
    roots = sorted_tiles[tile_components(sorted_tiles, near)]
    out = table.take(pa.array(order))
    for i, k in reversed(list(enumerate(keys))):
        out = out.add_column(0, f"r_{k}", pa.array(roots[:, i], pa.int64()))
    return out


def few_tiles(sig: DataFrame) -> pa.Table | None:
    """The tiles in one trip to the driver, or None when they are more than DRIVER_TILES."""
    found = sig.limit(DRIVER_TILES + 1).toArrow()
    return found if found.num_rows <= DRIVER_TILES else None


def seems_small(df: DataFrame) -> bool:
    """Whether the optimizer's estimate of what ``df`` reads says that it may be asked at once."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    return sum(int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.length())) <= SMALL_INPUT


def large_enough(labelled: pa.Table, keys: tuple[str, ...], mu: int) -> pa.Table:
    """Rows of clusters of at least ``mu`` tiles; a cluster's rows share its root."""
    if mu <= 1 or not labelled.num_rows:
        return labelled
    roots = np.stack([labelled[f"r_{k}"].to_numpy() for k in keys], 1)
    _, back, many = np.unique(roots, axis=0, return_inverse=True, return_counts=True)
    return labelled.filter(pa.array(many[back.ravel()] >= mu))


def _frame(sig: DataFrame, labelled: pa.Table) -> DataFrame:
    spark, schema = sig.sparkSession, _result_schema(sig)
    return spark.createDataFrame(labelled, schema) if labelled.num_rows else spark.createDataFrame([], schema)


def _driver(sig: DataFrame, near: Neighborhood, mu: int = 1) -> DataFrame | None:
    """One trip: the tiles come to the driver and go back labelled; None if they are too many."""
    tiles = few_tiles(sig)
    if tiles is None:
        return None
    keys = tile_keys(sig)
    return _frame(sig, large_enough(_label_table(tiles, keys, near), keys, mu))


def _star(sig: DataFrame, near: Neighborhood) -> DataFrame:
    return _named(sig, star_components(tile_edges(sig, near)))


def _propagate(sig: DataFrame, near: Neighborhood, max_rounds: int = 200) -> DataFrame:
    """Least label of the neighbourhood, then the label's label: no Python at all."""
    edges = tile_edges(sig, near)
    both = stage(edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), "edge")
    labels = stage(both.groupBy(F.col("src").alias("node")).agg(F.least(F.min("dst"), F.col("src")).alias("root")), "label")
    for _ in range(max_rounds):
        seen = both.join(labels.select(F.col("node").alias("dst"), "root"), "dst").groupBy(F.col("src").alias("node")).agg(F.min("root").alias("low"))
        moved = labels.join(seen, "node").select("node", F.col("root").alias("was"), F.least("root", "low").alias("root"))
        above = moved.select(F.col("node").alias("root"), F.col("root").alias("up"))
        jumped = stage(moved.join(above, "root").select("node", "was", F.least("root", "up").alias("root")), "label")
        changed = jumped.where("root <> was").limit(1).count()
        release(labels)
        labels = jumped.select("node", "root")
        labels._staged_at = jumped._staged_at
        if not changed:
            break
    return _named(sig, labels)


def _recursive(sig: DataFrame, near: Neighborhood, levels: int = 90) -> DataFrame:
    """A recursive query that carries reached pairs.

    Spark ends a recursion at a number of rows; a walk has a row for every tile and level,
    so that number is lifted while the sweeps run, and the levels bound the walk.
    """
    spark, keys = sig.sparkSession, tile_keys(sig)
    edges = tile_edges(sig, near)
    both = stage(edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))), "edge")
    labels = stage(both.groupBy("src").agg(F.least(F.min("dst"), F.col("src")).alias("root")), "label")
    both.createOrReplaceTempView("_walk_edges")
    labels.createOrReplaceTempView("_walk_start")
    # UNION of distinct rows is not allowed in a recursion: walk only downhill, so that
    # each path is a falling chain of labels, and leave the rest to the next sweep
    limit = spark.conf.get(RECURSION_ROWS, None)
    spark.conf.set(RECURSION_ROWS, "-1")
    try:
        while True:
            walked = stage(spark.sql(f"""
                WITH RECURSIVE walk(src, root, depth) AS (
                  SELECT src, root, 0 FROM _walk_start
                  UNION ALL
                  SELECT w.src, s.root, depth + 1 FROM walk w JOIN _walk_start s ON s.src = w.root WHERE s.root < w.root AND depth < {levels}
                ) SELECT src, min(root) AS root FROM walk GROUP BY src"""), "walk")
            walked.createOrReplaceTempView("_walked")
            after = stage(spark.sql("""
                SELECT w.src, least(first(w.root), min(o.root)) AS root FROM _walked w JOIN _walk_edges e ON e.src = w.src JOIN _walked o ON o.src = e.dst GROUP BY w.src"""), "label")
            settled = after.join(labels, "src").where(after["root"] != labels["root"]).isEmpty()
            release(walked, labels)
            labels = after
            labels.createOrReplaceTempView("_walk_start")
            if settled:
                break
    finally:
        if limit is None:
            spark.conf.unset(RECURSION_ROWS)
        else:
            spark.conf.set(RECURSION_ROWS, limit)
    return _named(sig.select(*sig.columns), labels.select(F.col("src").alias("node"), "root"))


def agglomerate(sig: DataFrame, near: Neighborhood | None = None, engine: str = "auto") -> DataFrame:
    """Clusters of significant tiles: ``r_<key>`` beside the input's columns.

    ``auto`` and ``driver`` take the driver up to DRIVER_TILES tiles and blocks beyond.
    """
    near = near or Neighborhood()
    if engine not in ENGINES:
        raise ValueError(f"engine is one of {ENGINES}")
    if engine in ("auto", "driver"):
        sig = sig if seems_small(sig) else stage(sig, "sig")
        found = _driver(sig, near)
        if found is not None:
            return found
    if engine in ("auto", "driver", "blocks"):
        from gridhub.operators.sliced import block_clusters

        return block_clusters(sig, near)
    sig = stage(sig, "sig")
    return {"star": _star, "propagate": _propagate, "recursive": _recursive}[engine](sig, near)


def keep_clusters(labelled: DataFrame, mu: int) -> DataFrame:
    """Clusters of at least ``mu`` tiles."""
    roots = [f"r_{k}" for k in tile_keys(labelled)]
    large = labelled.groupBy(*roots).agg(F.count("*").alias("_tiles")).where(F.col("_tiles") >= mu).drop("_tiles")
    return labelled.join(large, roots, "left_semi")


def tile_clusters(points: DataFrame, grid: Grid, params: TileParams | None = None, engine: str = "auto") -> DataFrame:
    """The base method: points to clusters of tiles; points are counted and forgotten."""
    params = params or TileParams()
    sig = significant(count_tiles(points, grid), params.tau)
    if engine == "auto":
        sig = sig if seems_small(sig) else stage(sig, "sig")
        found = _driver(sig, params.near, params.mu)
        if found is not None:
            return found
        engine = "blocks"
    return keep_clusters(agglomerate(sig, params.near, engine), params.mu)


def cluster_ids(clusters: DataFrame) -> DataFrame:
    """Adds ``cluster_id`` 0.. by root; the one-partition sort sees roots only."""
    from pyspark.sql import Window

    roots = [f"r_{k}" for k in tile_keys(clusters)]
    numbered = clusters.select(*roots).distinct().withColumn("cluster_id", (F.row_number().over(Window.orderBy(*roots)) - 1).cast("bigint"))
    return clusters.join(numbered, roots)


def nested_clusters(clusters: DataFrame) -> DataFrame:
    """One row per cluster with its tiles as a sorted array."""
    keys = tile_keys(clusters)
    return clusters.groupBy(*[f"r_{k}" for k in keys]).agg(F.array_sort(F.collect_list(F.struct(*keys, "n"))).alias("tiles"), F.sum("n").cast("bigint").alias("points"))
