"""What driver and executors share: durable intermediates, and the package itself; joins that bypass the driver."""

from __future__ import annotations

import atexit
import gc
import os
import shutil
import tempfile
import time
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

#: Only for local masters, where driver and executors are one process.
LOCAL_FALLBACK = "/tmp/checkpoints"
PACKAGE = Path(__file__).resolve().parent

_scratch: dict[str, list[str]] = {}


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; one of our own only where that is not set and the master is local."""
    context = spark.sparkContext
    given = context.getConf().get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not given:
        if not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        given = f"{LOCAL_FALLBACK}/{uuid.uuid4().hex}"
    if not context.getCheckpointDir():
        context.setCheckpointDir(given)
    return given


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder; tidy() removes it."""
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _scratch.setdefault(spark.sparkContext.applicationId, []).append(path)
    return path


def tidy(spark: SparkSession, paths: list[str] | None = None) -> int:
    """Removes scratch paths (all that this application asked for, or those given) from the shared folder."""
    mine = _scratch.get(spark.sparkContext.applicationId, [])
    gone = 0
    for path in list(mine if paths is None else paths):
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        gone += bool(where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True))
        if path in mine:
            mine.remove(path)
    return gone


def file_names(spark: SparkSession, path: str) -> list[str]:
    """Names of the files that Spark wrote into a folder, in the order of its partitions."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    found = where.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(where)
    return sorted(n for f in found if (n := f.getPath().getName()).startswith("part-"))


def local_path(spark: SparkSession, path: str) -> str | None:
    """The path that plain file calls take, if the folder is mounted as one; None for a store."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    uri = where.getFileSystem(spark._jsc.hadoopConfiguration()).makeQualified(where).toUri()
    return uri.getPath() if uri.getScheme() == "file" else None


def durable(df: DataFrame) -> DataFrame:
    """Computes df once and keeps it in the shared folder: lost executors lose nothing, lineage ends."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame, name: str) -> DataFrame:
    """Writes df as Parquet into the shared folder and reads it back: columnar, prunable, with a short plan."""
    path = scratch(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Lets Spark drop the shuffle files of frames that nobody holds any more: it does so when the driver collects its garbage.

    Python's references may reach the JVM only after its first collection, so there is a second one.
    """
    for wait in (0.2, 0):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(wait)


def ship(spark: SparkSession) -> None:
    """Sends this package to the executors once per context."""
    context = spark.sparkContext
    if getattr(context, "_package_shipped", False):
        return
    folder = tempfile.mkdtemp()  # the driver serves the file from here as long as it lives
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    archive = os.path.join(folder, f"{PACKAGE.name}-{uuid.uuid4().hex[:8]}.zip")
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as z:
        for path in sorted(PACKAGE.rglob("*.py")):
            z.write(path, path.relative_to(PACKAGE.parent))
    context.addPyFile(archive)
    context._package_shipped = True


def meet(left: DataFrame, right: DataFrame, keys: list[str], hint: str | None = None) -> DataFrame:
    """A join of two relations that may be far larger than Spark thinks: by sort and merge, or as the hint says.

    Spark takes what explode makes for no larger than the lists it comes from, and a table for no larger than
    its compressed files, so it would send a relation of any size through the driver. Both sides are
    shuffled, and spill where they do not fit.
    """
    return left.join(right.hint(hint or "merge"), keys)
