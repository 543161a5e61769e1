"""Tables in and out: Parquet, CSV, JSON, ORC, views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    """One Parquet table; columns are pruned by what the query uses."""
    return spark.read.parquet(f"{folder}/{name}.parquet")


def register(spark: SparkSession, folder: str, names: tuple[str, ...] = TABLES) -> None:
    """All tables as temporary views."""
    for n in names:
        table(spark, folder, n).createOrReplaceTempView(n)


def points_schema(axes: tuple[str, ...] = ("lon", "lat"), extra: dict[str, T.DataType] | None = None) -> T.StructType:
    fields = [T.StructField(a, T.DoubleType()) for a in axes] + [T.StructField(k, t) for k, t in (extra or {}).items()]
    return T.StructType([*fields, T.StructField("_malformed", T.StringType())])


def points_csv(spark: SparkSession, path: str, axes: tuple[str, ...] = ("lon", "lat"), header: bool = True) -> DataFrame:
    """Points from text with a given schema; broken rows keep their text in ``_malformed``."""
    return spark.read.schema(points_schema(axes)).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_malformed").csv(path, header=header)


def points_json(spark: SparkSession, path: str, axes: tuple[str, ...] = ("lon", "lat")) -> DataFrame:
    return spark.read.schema(points_schema(axes)).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_malformed").json(path)


def write_counts(counts: DataFrame, path: str, kind: str = "parquet") -> None:
    """Tile counts, replacing what is there; ``kind`` parquet, orc, csv or json."""
    counts.write.mode("overwrite").format(kind).save(path)


def read_counts(spark: SparkSession, path: str, kind: str = "parquet", dim: int = 2) -> DataFrame:
    keys = ("tx", "ty") if dim == 2 else tuple(f"t{i}" for i in range(dim))
    return spark.read.schema(", ".join(f"{k} bigint" for k in keys) + ", n bigint").format(kind).load(path)
