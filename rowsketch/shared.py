"""Scratch tables that every executor and the driver can read.

Lineage is cut by writing Parquet below the folder the cluster names in
``spark.checkpoint.dir``.  Only where a session names none and runs in one
process (local tests) is a folder of our own chosen; on a cluster that is an
error, as executors would write to disks of their own.  The tables of a session
stand in one folder, which goes when the session's JVM ends; a table that a
later one replaces can go before (:func:`discard`).
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: dict[str, str] = {}
_FOLDERS: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The session's shared scratch folder; a local one only if none is set and there is one process."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        option = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = option.get() if option.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = _LOCAL.setdefault("dir", "file://" + tempfile.mkdtemp(prefix="rowsketch-"))
    return found.rstrip("/")


def _hadoop(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where, where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def scratch(spark: SparkSession) -> str:
    """This application's own folder below the shared one; it is removed when the JVM ends."""
    folder = f"{shared_dir(spark)}/rowsketch-{spark.sparkContext.applicationId}"
    if _FOLDERS.get(spark.sparkContext.applicationId) != folder:
        where, system = _hadoop(spark, folder)
        system.mkdirs(where)
        system.deleteOnExit(where)
        _FOLDERS[spark.sparkContext.applicationId] = folder
    return folder


def materialise(df: DataFrame, name: str = "table") -> DataFrame:
    """Write ``df`` once to the shared folder and read it back.

    The written files replace the lineage, so a lost executor costs a reread
    and not a recomputation.
    """
    spark = df.sparkSession
    path = f"{scratch(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._rowsketch_path = path
    return out


def discard(df: DataFrame | None) -> None:
    """Removes a table of :func:`materialise` that nothing will read again; other DataFrames are left alone."""
    path = getattr(df, "_rowsketch_path", None)
    if isinstance(path, str):
        where, system = _hadoop(df.sparkSession, path)
        system.delete(where, True)


_SHIPPED: dict[str, str] = {}


def ship(spark: SparkSession) -> None:
    """Sends this package to the executors once an application, for sessions whose workers do not have it on their path."""
    import os
    import zipfile

    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="rowsketch-ship-"), "rowsketch.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(folder, name)
                    z.write(full, os.path.join("rowsketch", os.path.relpath(full, root)))
    spark.sparkContext.addPyFile(path)
    _SHIPPED[app] = path
