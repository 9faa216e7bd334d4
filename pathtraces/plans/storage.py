"""Shared storage for what is read more than once, and broadcasts whose size was checked first."""

from __future__ import annotations

import atexit
import contextlib
import logging
import uuid
from collections.abc import Iterator

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows that may be sent to every task.
BROADCAST_ROWS = 200_000

#: Paths with the JVM and the Hadoop settings to delete them by, which outlive the session.
_written: list[tuple[object, object, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, from ``spark.checkpoint.dir``; one of our own where that is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        return "/tmp/checkpoints/pathtraces"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_pathtraces"


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder, deleted at the end of the innermost ``released`` block, or when the driver's process ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    if not _written:
        atexit.register(release)
    _written.append((spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration(), path))
    return path


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: one computation, short lineage, no data that a lost executor takes along."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def release(keep: int = 0) -> None:
    """Delete all that was stored, but for the first ``keep`` paths; also after the session has been stopped."""
    while len(_written) > keep:
        jvm, settings, path = _written.pop()
        try:
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(settings).delete(at, True)
        except (Py4JError, OSError) as failed:  # the JVM is gone, or the folder
            logging.getLogger(__name__).warning("not deleted: %s (%s)", path, type(failed).__name__)


@contextlib.contextmanager
def released() -> Iterator[None]:
    """What is stored inside the block is deleted at its end: results must have been written or collected by then."""
    before = len(_written)
    try:
        yield
    finally:
        release(before)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``rows`` rows; otherwise as it is, for a join by shuffle. ``df`` should be
    materialised: it is counted up to that bound."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df
