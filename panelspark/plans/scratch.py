"""Lineage cuts through a folder that all executors share."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame


def folder(spark) -> str:
    """A fresh folder below spark.checkpoint.dir; where that is unset, on a local master only, below a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None) or os.environ.get("PANELSPARK_SCRATCH")
    if not base:
        if spark.conf.get("spark.master", "local").split("[")[0] != "local":
            raise RuntimeError("on a cluster, spark.checkpoint.dir must name a folder that all executors share")
        base = tempfile.gettempdir() + "/panelspark-scratch"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def settled(df: DataFrame) -> DataFrame:
    """df written as Parquet and read again; survives the loss of executors."""
    path = folder(df.sparkSession)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.settled_at = path
    return out


def discard(*steps: DataFrame) -> None:
    """Deletes the files of settled frames that nothing reads any more."""
    for step in steps:
        path = step.sparkSession._jvm.org.apache.hadoop.fs.Path(step.settled_at)
        path.getFileSystem(step.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(path, True)
