"""What a cluster needs from the driver: the package's code on every executor, and a folder that all can reach."""

from __future__ import annotations

import contextlib
import os
import tempfile
import uuid
import zipfile

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> None:
    """Send this package's code to the executors once per Spark context, so that Arrow functions import everywhere."""
    sc = spark.sparkContext
    if getattr(sc, "_approxset_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    target = os.path.join(tempfile.mkdtemp(prefix="approxset"), "approxset.zip")
    with zipfile.ZipFile(target, "w") as z:
        for folder, _, names in os.walk(root):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.join("approxset", os.path.relpath(full, root)))
    sc.addPyFile(target)
    sc._approxset_shipped = True


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local session may do without (as in tests): it
    gets a temporary one. Elsewhere a machine's own folder would hold a part of the data only, so an unset one is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    sc = spark.sparkContext
    if not sc.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not getattr(sc, "_approxset_shared", None):
        sc._approxset_shared = "file://" + tempfile.mkdtemp(prefix="approxset-shared")
    return sc._approxset_shared


def work_folder(spark: SparkSession) -> str:
    """A new folder inside the shared one."""
    return f"{shared_folder(spark)}/{uuid.uuid4().hex}"


@contextlib.contextmanager
def cleaned(spark: SparkSession):
    """Inside it, what a query shuffled is deleted as soon as the query has ended, not when the driver's objects are collected."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def drop_folder(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
