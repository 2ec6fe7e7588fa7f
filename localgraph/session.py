"""Durable intermediate tables: written to the folder that driver and executors share, dropped when used up."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[int, str] = {}
_AT: weakref.WeakKeyDictionary[DataFrame, str] = weakref.WeakKeyDictionary()
_LEFT: dict[str, SparkSession] = {}


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which driver and executors share; a temporary folder only in plain local mode."""
    if there := spark.conf.get("spark.checkpoint.dir", None):
        return there.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    key = id(spark.sparkContext)
    if key not in _OWN:
        _OWN[key] = tempfile.mkdtemp(prefix="engine-steps-")
        atexit.register(shutil.rmtree, _OWN[key], True)
    return _OWN[key]


def cut(df: DataFrame, label: str = "step", by: list[str] | None = None) -> DataFrame:
    """df written to the shared folder, in folders by columns if given, and read back: cuts lineage and outlives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path, partitionBy=by)
    out = spark.read.schema(df.schema).parquet(path)
    _AT[out], _LEFT[path] = path, spark
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def drop(*frames: DataFrame) -> None:
    """Remove tables that `cut` wrote and nothing will read again; other frames are left alone."""
    for df in frames:
        if path := _AT.pop(df, None):
            _delete(_LEFT.pop(path), path)


@atexit.register
def _drop_rest() -> None:
    """Tables behind results that were handed out go when the driver ends."""
    for path, spark in _LEFT.items():
        with contextlib.suppress(Exception):
            _delete(spark, path)
