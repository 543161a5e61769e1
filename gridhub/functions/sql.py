"""The SQL surface: views, functions and a table function."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import DoubleType

from gridhub.config import Neighborhood
from gridhub.operators.neighbors import register_neighbors
from gridhub.operators.unionfind import tile_components


def register_functions(spark: SparkSession) -> None:
    """``tile_of(x, scale)``, ``tile_neighbors(...)`` and ``tile_components(TABLE ...)``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tile_of(x DOUBLE, scale DOUBLE) RETURNS BIGINT RETURN CAST(floor(x * scale) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tile_area_m2(lat DOUBLE, scale DOUBLE) RETURNS DOUBLE RETURN pow(111194.92664455873 / scale, 2) * cos(radians(lat))")
    register_neighbors(spark)
    spark.udtf.register("tile_components", TileComponents)


@udtf(returnType="r_tx bigint, r_ty bigint, tx bigint, ty bigint, n bigint")
class TileComponents:
    """``SELECT * FROM tile_components(TABLE(t) WITH SINGLE PARTITION)`` or by a slice.

    Local components of the tiles of one partition, at Chebyshev distance 1.
    """

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["tx"], row["ty"], row["n"]))

    def terminate(self):
        import numpy as np

        self.rows.sort()
        tiles = np.array([r[:2] for r in self.rows], np.int64).reshape(-1, 2)
        roots = tiles[tile_components(tiles, Neighborhood())]
        for (tx, ty, n), (rx, ry) in zip(self.rows, roots.tolist()):
            yield rx, ry, tx, ty, n


@F.pandas_udf(DoubleType())
def tile_entropy(weights: pd.Series) -> float:
    """A user's density function per tile, as a grouped aggregate."""
    import numpy as np

    p = weights.to_numpy(float)
    p = p[p > 0] / p[p > 0].sum() if (p > 0).any() else p[:0]
    return float(-(p * np.log2(p)).sum())


def point_in_polygon(corners: list[tuple[float, float]]):
    """The polygon test as an Arrow-batched function, for polygons of very many corners."""

    @F.pandas_udf("boolean")
    def inside(x: pd.Series, y: pd.Series) -> pd.Series:
        import numpy as np

        out = np.zeros(len(x), bool)
        for (x1, y1), (x2, y2) in zip(corners, corners[1:] + corners[:1]):
            if y1 != y2:
                straddles = (y1 > y.to_numpy()) != (y2 > y.to_numpy())
                out ^= straddles & (x.to_numpy() < (x2 - x1) * (y.to_numpy() - y1) / (y2 - y1) + x1)
        return pd.Series(out)

    return inside


def map_side_counts(tiled: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """Partial counts per task in Arrow batches, for engines without map-side aggregation."""

    def count(batches):
        for b in batches:
            yield from pa.Table.from_batches([b]).group_by(list(keys)).aggregate([([], "count_all")]).rename_columns([*keys, "n"]).to_batches()

    return tiled.select(*keys).mapInArrow(count, ", ".join(f"{k} bigint" for k in keys) + ", n bigint")


def clusters_geojson(hub_rows: DataFrame, degrees: float = 1.0) -> DataFrame:
    """One JSON feature per hub."""
    feature = F.struct(F.lit("Feature").alias("type"), F.struct(F.lit("Point").alias("type"), F.array(F.col("x") * degrees, F.col("y") * degrees).alias("coordinates")).alias("geometry"), F.struct("tiles", "points").alias("properties"))
    return hub_rows.select(F.to_json(feature).alias("feature"))


def props_number(props: Column, name: str = "k") -> Column:
    """A number out of a JSON column of flat properties."""
    return F.from_json(props, "map<string,int>")[name]
