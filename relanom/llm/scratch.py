"""Intermediate tables in the shared folder that the session names.

A written table cuts lineage, survives a lost executor and can be read by every
node; ``localCheckpoint`` and machine-local folders are never used.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid
import weakref

from pyspark.sql import DataFrame, SparkSession

_written: dict[str, SparkSession] = {}
_paths: dict[int, tuple] = {}


def folder(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; where it is unset, a folder of our own on a single machine and an error on a cluster."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("spark.checkpoint.dir must name a folder that all nodes share")
        where = "file://" + tempfile.mkdtemp(prefix="relanom-scratch-")
        spark.conf.set("spark.checkpoint.dir", where)
    return where.rstrip("/")


def table(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and return a DataFrame that reads it back."""
    spark = df.sparkSession
    path = f"{folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _written[path] = spark
    _paths[id(out)] = (weakref.ref(out), path)
    return out


def drop(*tables: DataFrame) -> None:
    """Delete tables made by ``table`` that nothing reads any more."""
    for df in tables:
        held, path = _paths.pop(id(df), (None, None))
        if held and held() is df and path in _written:
            _delete(_written.pop(path), path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def cleanup() -> None:
    """Delete the tables this driver wrote; call it when their results are no longer read."""
    while _written:
        path, spark = _written.popitem()
        try:
            _delete(spark, path)
        except Exception:  # the session has ended; the folder's owner removes it
            return
