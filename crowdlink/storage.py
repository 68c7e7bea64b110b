"""Cutting lineage: tables written in the folder that the cluster names in ``spark.checkpoint.dir``."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Paths that this process has written and not yet removed, with their sessions.
_written: dict[str, SparkSession] = {}


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors share; only a session on one machine may go without one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.conf.get("spark.master", "").startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return f"{tempfile.gettempdir()}/crowdlink-checkpoints"


def new_path(spark: SparkSession, label: str) -> str:
    """A path of its own in the shared folder, removed when the process ends."""
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    _written[path] = spark
    return path


def cut(df: DataFrame, label: str = "step") -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again with the same schema.

    Later steps survive the loss of an executor, scan only the columns they need, and never
    recompute what lies before the cut. The table goes when the process ends, or earlier by ``forget``.
    """
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.cut_path = path
    return out


def forget(*tables: DataFrame | None) -> None:
    """Remove tables that ``cut`` gave and that nothing reads any more."""
    for t in tables:
        path = getattr(t, "cut_path", None)
        if path in _written:
            _remove(_written.pop(path), path)


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


@atexit.register
def _sweep() -> None:
    for path, spark in list(_written.items()):
        with contextlib.suppress(Exception):  # the session may be gone; then its folder is swept by the cluster
            _remove(spark, path)
