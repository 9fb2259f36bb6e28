"""Lineage cuts: tables written once in the cluster's shared folder."""

from __future__ import annotations

import re
import tempfile
import threading
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame

_FREE, _lock, _writes = "spark.sql.classic.shuffleDependency.fileCleanup.enabled", threading.Lock(), [0, None]


@contextmanager
def _freeing(spark):
    """While tables are written, Spark removes a write's shuffle files at its end, rather than when the driver collects garbage."""
    with _lock:
        if not _writes[0]:
            _writes[1] = spark.conf.get(_FREE, None)
            spark.conf.set(_FREE, "true")
        _writes[0] += 1
    try:
        yield
    finally:
        with _lock:
            _writes[0] -= 1
            if not _writes[0]:
                spark.conf.unset(_FREE) if _writes[1] is None else spark.conf.set(_FREE, _writes[1])


def shared_folder(spark) -> str:
    """``spark.checkpoint.dir`` of the session.

    Where it is unset, a temporary folder is set if driver and tasks are one machine (``local``, as in tests); on a
    cluster that is an error, since a machine's own folder would lose the tables.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="streamcut-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def keep(df: DataFrame, name: str = "t") -> DataFrame:
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex[:12]}"
    with _freeing(df.sparkSession):
        df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def drop(*frames: DataFrame | None) -> None:
    """Removes tables made by ``keep`` that no later plan reads; others are left alone."""
    for df in frames:
        if path := getattr(df, "_scratch_path", None):
            spark = df.sparkSession
            path = spark._jvm.org.apache.hadoop.fs.Path(path)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
