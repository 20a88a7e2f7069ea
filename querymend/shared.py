"""The shared folder of the cluster."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid

from pyspark.sql import SparkSession

_made: list[tuple[SparkSession, str]] = []


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of any file system that Spark reaches."""
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


@atexit.register
def clear() -> None:
    """Delete the folders that this process made: results are read lazily, so
    they are in use until it ends, or until the caller says so."""
    while _made:
        spark, path = _made.pop()
        with contextlib.suppress(Exception):  # the session may be gone
            remove(spark, path)


def workspace(spark: SparkSession, prefix: str = "work") -> str:
    """A new folder below ``spark.checkpoint.dir``. Where that is unset, one of
    our own, but only on a single machine (``local[..]``, as in tests):
    executors of a cluster do not share such a folder."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        folder = tempfile.mkdtemp(prefix=f"{prefix}-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        root = f"file://{folder}"
    path = f"{root.rstrip('/')}/{prefix}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path
