"""Shared folders of a session: cutting lineage, passing files on, and deleting them."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def settled(df: DataFrame) -> DataFrame:
    """Cut the lineage of ``df`` through the shared checkpoint folder of the session."""
    base = shared_base(df.sparkSession)
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(base)
    return df.checkpoint()


def shared_base(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names. Where none is set (tests, a laptop: local mode only)
    one is chosen on this machine; a cluster without one is refused, since its executors share no local folder."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"file://{tempfile.gettempdir()}/checkpoints-{os.getpid()}"


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder of the session, for files that a later stage reads."""
    return f"{shared_base(spark)}/{name}-{uuid.uuid4().hex}"


def remove(spark: SparkSession, folder: str) -> None:
    """Delete a folder of ``shared_folder`` that no one reads any more."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
