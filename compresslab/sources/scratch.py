"""Paths for intermediate tables in the shared folder that the cluster names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_marked: set[str] = set()


def scratch_root(spark: SparkSession) -> str:
    """This application's folder below spark.checkpoint.dir; it is deleted when the driver's JVM ends.

    Only a local session that names no folder gets one of its own; a cluster must name a shared one.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            named = current.get()
        elif spark.sparkContext.master.startswith("local"):
            named = tempfile.mkdtemp(prefix="compresslab-")
            spark.sparkContext.setCheckpointDir(named)
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    root = f"{named.rstrip('/')}/compresslab/{spark.sparkContext.applicationId}"
    if root not in _marked:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(root)
        files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        files.mkdirs(path)
        files.deleteOnExit(path)
        _marked.add(root)
    return root


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str, options: dict[str, str] | None = None) -> DataFrame:
    """Write df once to the shared folder and read it back: the lineage is cut, and a lost executor costs a
    re-read, never a recomputation of everything above. options: of the Parquet writer."""
    path = scratch_path(df.sparkSession, label)
    df.write.options(**(options or {})).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
