"""Tile neighbours as an equi-join: offsets are a literal array, never a range join."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from gridhub.config import Neighborhood


def tile_keys(tiles: DataFrame) -> tuple[str, ...]:
    """Tile columns by name: tx, ty or t0, t1, ..."""
    if "tx" in tiles.columns:
        return ("tx", "ty")
    return tuple(sorted((c for c in tiles.columns if c[0] == "t" and c[1:].isdigit()), key=lambda c: int(c[1:])))


def neighbours(tiles: DataFrame, near: Neighborhood, half: bool = False) -> DataFrame:
    """Each tile with the places around it: ``tile`` columns kept, neighbour as ``n_<key>``."""
    keys = tile_keys(tiles)
    offsets = near.half_offsets(len(keys)) if half else near.all_offsets(len(keys))
    table = F.array(*[F.struct(*[F.lit(x).cast("bigint").alias(f"d{i}") for i, x in enumerate(o)]) for o in offsets])
    moved = tiles.withColumn("_o", F.explode(table))
    return moved.withColumns({f"n_{k}": F.col(k) + F.col(f"_o.d{i}") for i, k in enumerate(keys)}).drop("_o")


def tile_edges(tiles: DataFrame, near: Neighborhood) -> DataFrame:
    """``src, dst`` structs of tile keys for each pair of tiles within reach, once."""
    keys = tile_keys(tiles)
    around = neighbours(tiles.select(*keys), near, half=True)
    other = tiles.select(*[F.col(k).alias(f"n_{k}") for k in keys])
    met = around.join(other, [f"n_{k}" for k in keys])
    return met.select(F.struct(*keys).alias("src"), F.struct(*[F.col(f"n_{k}").alias(k) for k in keys]).alias("dst"))


@udtf(returnType="ntx bigint, nty bigint")
class TileNeighbors:
    """SQL table function: the neighbours of a tile."""

    def eval(self, tx: int, ty: int, metric: str, delta: int):
        for dx, dy in Neighborhood(metric, delta).all_offsets(2):
            yield tx + dx, ty + dy


def register_neighbors(spark: SparkSession, name: str = "tile_neighbors") -> None:
    spark.udtf.register(name, TileNeighbors)
