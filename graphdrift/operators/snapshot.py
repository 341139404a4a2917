"""Snapshots of intermediate state: parquet by iteration, valid once marked."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _fs(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p, p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def save_snapshot(state: DataFrame, path: str, iteration: int, run_id: str = "run") -> None:
    """Write the state of an iteration; the mark goes last, so a torn write is never read."""
    spark, at = state.sparkSession, f"{path}/run_id={run_id}/iteration={iteration}"
    state.write.mode("overwrite").parquet(at)
    p, fs = _fs(spark, f"{at}/_COMMITTED")
    fs.create(p, True).close()


def restore_latest(spark: SparkSession, path: str, run_id: str = "run") -> tuple[DataFrame | None, int]:
    """The newest committed state and its iteration (None, 0 if there is none)."""
    p, fs = _fs(spark, f"{path}/run_id={run_id}")
    if not fs.exists(p):
        return None, 0
    done = []
    for s in fs.listStatus(p):
        child = s.getPath().toString()
        mark, _ = _fs(spark, f"{child}/_COMMITTED")
        if fs.exists(mark):
            done.append((int(child.rsplit("=", 1)[1]), child))
    if not done:
        return None, 0
    iteration, at = max(done)
    return spark.read.parquet(at), iteration


def history_sink(history: DataFrame, path: str) -> None:
    """Append a metrics history."""
    history.withColumn("written", F.current_timestamp()).write.mode("append").parquet(path)
