"""Intermediate tables in the folder that every executor and the driver share.

Iterative plans and plans that read a result twice cut their lineage here: the
rows are written once as Parquet below ``spark.checkpoint.dir`` and read back,
so a lost executor costs a re-read and no recomputation.
"""

from __future__ import annotations

import atexit
import re
import uuid
from weakref import WeakKeyDictionary

from pyspark.sql import DataFrame, SparkSession

#: Used only on one machine, where the session names no folder, as in local tests.
LOCAL_DEFAULT = "file:///tmp/checkpoints/roadweave"

_written: list[tuple[SparkSession, str]] = []
_path_of: WeakKeyDictionary[DataFrame, str] = WeakKeyDictionary()


def shared_folder(spark: SparkSession) -> str:
    """The shared folder of the session; on one machine there is a default."""
    named = spark.conf.get("spark.checkpoint.dir", "") or ""
    if not named and not re.match(r"local($|\[)", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    jvm = spark.sparkContext._jvm
    folder = jvm.org.apache.hadoop.fs.Path((named or LOCAL_DEFAULT).rstrip("/"))
    # With its scheme, as workers open files there by themselves.
    whole = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).makeQualified(folder).toString()
    return re.sub(r"^file:/(?!/)", "file:///", whole)


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder; it is removed when the driver ends."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once to the shared folder and return the table read back."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    table = spark.read.schema(df.schema).parquet(path)
    _path_of[table] = path
    return table


def discard(table: DataFrame) -> None:
    """Remove a table of :func:`materialise` from which nothing will be read again."""
    if path := _path_of.pop(table, None):
        release(table.sparkSession, path)


def release(spark: SparkSession, path: str) -> None:
    """Remove a path that :func:`new_path` gave out."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _release_all() -> None:
    for spark, path in _written:
        try:
            release(spark, path)
        except Exception:  # the session may have ended before the driver does
            return
