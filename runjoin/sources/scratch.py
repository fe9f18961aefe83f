"""Cutting lineage through the folder that driver and executors share."""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir, or the checkpoint folder set; only a session on one machine may do without and gets a local one."""
    context = spark.sparkContext
    root = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not root:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file:///tmp/checkpoints"
    if not context.getCheckpointDir():
        context.setCheckpointDir(root)
    return root.rstrip("/")


def folder(spark: SparkSession, label: str) -> str:
    """A new folder's address under the shared root; deleted when the driver's Python ends."""
    uri = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    atexit.register(remove, uri)
    return uri


def remove(uri: str) -> None:
    import pyarrow as pa
    import pyarrow.fs as pafs

    try:
        fs, path = pafs.FileSystem.from_uri(uri)
        fs.delete_dir(path)
    except (OSError, pa.ArrowException):
        pass


def materialise(df: DataFrame) -> DataFrame:
    """Compute once and keep on the shared folder, so that later uses start from files that outlive executors."""
    shared_root(df.sparkSession)
    return df.checkpoint(eager=True)
