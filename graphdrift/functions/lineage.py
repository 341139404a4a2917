"""Reliable checkpoints and checked broadcasts."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a counted side is broadcast.
BROADCAST_ROWS = 200_000


def checkpoint_dir(spark: SparkSession) -> str:
    """The session's shared checkpoint folder; our own only in local mode where none is set."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if not found:
        found = sc.getConf().get("spark.checkpoint.dir")
        if not found and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        found = found or os.path.join(tempfile.gettempdir(), "graphdrift-checkpoints")
        sc.setCheckpointDir(found)
    return found


@contextmanager
def setting(spark: SparkSession, key: str, value: str) -> Iterator[None]:
    """A session's setting for what is planned meanwhile."""
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder and forget the lineage; survives lost executors. Its shuffles' files go at once, not when the driver collects garbage."""
    checkpoint_dir(df.sparkSession)
    with setting(df.sparkSession, "spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true"):
        # a plan of its own: what else is asked of the frame has its own shuffles
        return df.select("*").checkpoint(eager=True)


def forget(*frames: DataFrame) -> None:
    """Delete the files of checkpoints that nothing reads any more."""
    for df in frames:
        file = df._jdf.queryExecution().logical().rdd().getCheckpointFile()
        if file.isDefined():
            sc = df.sparkSession.sparkContext
            path = sc._jvm.org.apache.hadoop.fs.Path(file.get())
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def broadcast_if_small(df: DataFrame, rows: int) -> DataFrame:
    """A broadcast hint when the counted ``rows`` are within the bound, else a plain join side."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df
