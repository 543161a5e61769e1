"""Lineage cuts that survive lost executors.

An iterative plan has to be cut now and then.  ``stage`` writes the rows as Parquet into
the folder that the cluster shares (``spark.checkpoint.dir``) and reads them back, so a
lost executor costs nothing and the reader keeps column pruning and true sizes.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own_root: str | None = None
#: Name of this process's folder.
_RUN = uuid.uuid4().hex


def shared_root(spark: SparkSession) -> str:
    """Folder for staged tables of this process, below ``spark.checkpoint.dir``.

    Without that setting a local session gets a temporary folder: one machine, so every
    task sees it.  On a cluster there is no folder that all executors surely share, so the
    setting is required.
    """
    global _own_root
    given = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if given:
        return f"{given.rstrip('/')}/gridhub/{_RUN}"
    if spark.sparkContext.master.split("[")[0] != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    if _own_root is None:
        _own_root = tempfile.mkdtemp(prefix="gridhub-stage-")
        atexit.register(shutil.rmtree, _own_root, ignore_errors=True)
    return "file://" + _own_root


def stage(df: DataFrame, name: str = "t", codec: str = "zstd") -> DataFrame:
    """Write ``df`` once to shared storage and return a DataFrame that reads it."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def release(*frames: DataFrame) -> None:
    """Delete the files behind staged frames that no later plan reads."""
    for df in frames:
        path = getattr(df, "_staged_at", None)
        if path:
            _delete(df.sparkSession, path)


def release_all(spark: SparkSession) -> None:
    """Delete everything that this process staged, once its results are written elsewhere."""
    _delete(spark, shared_root(spark))
