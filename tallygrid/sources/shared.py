"""The folder that driver and executors share, and tables kept there between steps of a job."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_local: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that the session names in spark.checkpoint.dir.

    Where none is named, a session that runs in this one process gets a temporary folder, removed at its end; on a cluster that is an error, as files in a
    machine's own folder are lost to the others.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _local:
        _local.append(tempfile.mkdtemp(prefix="shared-"))
        atexit.register(shutil.rmtree, _local[0], ignore_errors=True)
    return _local[0]


def place(spark: SparkSession, kind: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/{kind}-{uuid.uuid4().hex}"


def keep(df: DataFrame, kind: str = "kept", by: str | None = None) -> DataFrame:
    """Write `df` to the shared folder and go on from the files: what stands above reads them, not its sources."""
    path = place(df.sparkSession, kind)
    write = df.write.partitionBy(by) if by else df.write
    write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
