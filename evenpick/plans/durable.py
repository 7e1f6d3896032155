"""Lineage cuts that survive lost executors, and shipping of this package to the workers."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder shared by driver and executors: ``spark.checkpoint.dir`` of the session.

    Where the setting is missing, a temporary folder is made for a local master; on a cluster that is an error.
    """
    sc = spark.sparkContext
    configured = sc.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    current = sc._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    if not configured:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        configured = tempfile.mkdtemp(prefix="evenpick-checkpoints-")
    sc.setCheckpointDir(configured)
    return sc._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the lineage ends in files that every executor can read."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


@contextmanager
def swept(spark: SparkSession):
    """Queries begun inside leave no shuffle files behind: what they return or write does not need them, and the next shuffle needs the disk."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def staged(df: DataFrame, label: str, codec: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back (columnar, compressed lineage cut).

    ``codec`` trades the executors' native memory for disk ('zstd'); None is the session's own.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/staged/{label}-{uuid.uuid4().hex}"
    with swept(spark):
        (df.write.option("compression", codec) if codec else df.write).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_staged(df: DataFrame) -> None:
    """Delete the staged tables that ``df`` reads; nothing that reads them may be used afterwards. Other inputs are left alone."""
    spark = df.sparkSession
    top = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/staged")
    fs = top.getFileSystem(spark._jsc.hadoopConfiguration())
    top = fs.makeQualified(top)
    for path in {os.path.dirname(f) for f in df.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(path)
        if fs.makeQualified(path).getParent().equals(top):
            fs.delete(path, True)


def clear_staged(spark: SparkSession) -> None:
    """Delete all staged tables of the shared folder; frames that still read them must not be used afterwards."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/staged")
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors once per application, wherever it was imported from."""
    sc = spark.sparkContext
    if getattr(sc, "_evenpick_shipped", False):
        return
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    top = os.path.dirname(root)
    archive = os.path.join(tempfile.mkdtemp(prefix="evenpick-code-"), "evenpick_code.zip")
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.relpath(full, top))
    sc.addPyFile(archive)
    sc._evenpick_shipped = True


def maybe_broadcast(df: DataFrame, max_rows: int) -> DataFrame:
    """Broadcast hint behind a measured row count; beyond it the planner's shuffle join is kept."""
    return F.broadcast(df) if df.limit(max_rows + 1).count() <= max_rows else df


def shuffle_width(spark: SparkSession) -> int:
    """Partitions that an explicit repartition by key should use: the session's own setting."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
