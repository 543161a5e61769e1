"""Tile clustering as an estimator and a model of pyspark.ml pipelines."""

from __future__ import annotations

import json

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridhub.config import Grid, Neighborhood, TileParams
from gridhub.operators.agglomerate import cluster_ids, tile_clusters
from gridhub.operators.variants import label_points
from gridhub.plans.staging import stage


class _TileParams(Params):
    axes = Param(Params._dummy(), "axes", "axis columns", TypeConverters.toListString)
    precision = Param(Params._dummy(), "precision", "decimal precision", TypeConverters.toFloat)
    tau = Param(Params._dummy(), "tau", "points per significant tile", TypeConverters.toInt)
    mu = Param(Params._dummy(), "mu", "tiles per cluster", TypeConverters.toInt)
    metric = Param(Params._dummy(), "metric", "chebyshev or manhattan", TypeConverters.toString)
    delta = Param(Params._dummy(), "delta", "distance of neighbours", TypeConverters.toInt)
    predictionCol = Param(Params._dummy(), "predictionCol", "label column, -1 for noise", TypeConverters.toString)

    def _defaults(self) -> None:
        self._setDefault(axes=["lon", "lat"], precision=3.5, tau=5, mu=4, metric="chebyshev", delta=1, predictionCol="prediction")

    def grid(self) -> Grid:
        return Grid(tuple(self.getOrDefault("axes")), precision=self.getOrDefault("precision"))

    def thresholds(self) -> TileParams:
        return TileParams(self.getOrDefault("tau"), self.getOrDefault("mu"), Neighborhood(self.getOrDefault("metric"), self.getOrDefault("delta")))


class TileClusterer(Estimator, _TileParams, DefaultParamsReadable, DefaultParamsWritable):
    """Fits clusters of tiles; the model labels points."""

    @keyword_only
    def __init__(self, *, axes=None, precision=None, tau=None, mu=None, metric=None, delta=None, predictionCol=None):
        super().__init__()
        self._defaults()
        self._set(**{k: v for k, v in self._input_kwargs.items() if v is not None})

    def _fit(self, dataset: DataFrame) -> TileClusterModel:
        clusters = stage(cluster_ids(tile_clusters(dataset, self.grid(), self.thresholds())), "model")
        return self._copyValues(TileClusterModel(clusters))


class TileClusterModel(Model, _TileParams):
    """Clusters as a table; ``transform`` is the second pass over points."""

    def __init__(self, clusters: DataFrame | None = None):
        super().__init__()
        self._defaults()
        self.clusters = clusters

    def _transform(self, dataset: DataFrame) -> DataFrame:
        grid = self.grid()
        keys = list(grid.keys)
        table = self.clusters.select(*keys, "cluster_id")
        from gridhub.operators.project import with_tile

        out = self.getOrDefault("predictionCol")
        return with_tile(dataset, grid).join(table, keys, "left").withColumn(out, F.coalesce("cluster_id", F.lit(-1)).cast("bigint")).drop("cluster_id", *keys)

    def save(self, path: str) -> None:
        spark = self.clusters.sparkSession
        self.clusters.write.parquet(f"{path}/clusters")
        values = {p.name: self.getOrDefault(p) for p in self.params}
        spark.createDataFrame([(json.dumps(values),)], "params string").coalesce(1).write.text(f"{path}/params")

    @staticmethod
    def load(spark: SparkSession, path: str) -> TileClusterModel:
        model = TileClusterModel(spark.read.parquet(f"{path}/clusters"))
        model._set(**json.loads(spark.read.text(f"{path}/params").first()[0]))
        return model


__all__ = ["TileClusterModel", "TileClusterer", "label_points"]
