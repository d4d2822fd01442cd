"""Tables written between steps: they cut lineage and outlive executors."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def is_local(spark: SparkSession) -> bool:
    """Whether driver and executors are one process, and so share its folders and code."""
    return re.match(r"local(\[|$)", spark.sparkContext.master) is not None


def shared_dir(spark: SparkSession) -> str:
    """This run's own folder in spark.checkpoint.dir, which driver and executors share.

    Where that is unset a local session gets a folder of its own; on a cluster its executors could not read one, so it is an error.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if base is None and not is_local(spark):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    if base is None:
        base = _own_dir()
    return f"{base.rstrip('/')}/orderstat-{spark.sparkContext.applicationId}"


def _own_dir() -> str:
    if not _own:
        _own.append("file://" + tempfile.mkdtemp(prefix="orderstat-"))
    return _own[0]


_own: list[str] = []


def cleanup(spark: SparkSession) -> None:
    """Deletes this run's folder, when no result that reads from it is needed any more."""
    path = spark._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written once to the shared folder and read back."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
