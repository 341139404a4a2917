"""Helpers shared by the text operators: shared-folder checkpoints, byte access, Arrow batches."""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows in one Arrow batch handed to Python; texts are long, so batches stay small.
BATCH_ROWS = 1000


def tune(spark: SparkSession) -> None:
    """Bound the size of Arrow batches (a runtime setting of the session)."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def checkpoint_dir(spark: SparkSession) -> str:
    """The cluster's shared checkpoint folder; a folder of our own only in local mode where none is set."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if not found:
        found = sc.getConf().get("spark.checkpoint.dir")
        if not found and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        found = found or os.path.join(tempfile.gettempdir(), "graphdrift-checkpoints")
        sc.setCheckpointDir(found)
    return found


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared folder and forget its lineage.

    Reliable: every executor reads the same files. ``forget`` deletes them; those of
    frames that a result still reads go with Spark's cleaner, if the cluster sets
    spark.cleaner.referenceTracking.cleanCheckpoints.
    """
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a file or folder wherever Spark can reach it."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def forget(*frames: DataFrame) -> None:
    """Delete the files of frames that ``cut`` gave and that nothing reads any more."""
    for df in frames:
        file = df._jdf.queryExecution().logical().rdd().getCheckpointFile()
        if file.isDefined():
            delete(df.sparkSession, file.get())


def stored(df: DataFrame) -> tuple[DataFrame, str]:
    """``df`` written as (compressed) Parquet in the shared folder and read again, and the folder, for ``delete``."""
    spark = df.sparkSession
    path = f"{checkpoint_dir(spark)}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def bucketed(df: DataFrame, buckets: int, *columns: str) -> tuple[DataFrame, str]:
    """``df`` as a table in the shared folder, bucketed so that a join by ``columns`` needn't move it, and its name, for ``drop``."""
    spark, name = df.sparkSession, f"graphdrift_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, *columns).format("parquet").option("path", f"{checkpoint_dir(spark)}/{name}").saveAsTable(name)
    return spark.table(name), name


def drop(spark: SparkSession, name: str) -> None:
    """Remove a table of ``bucketed``."""
    spark.sql(f"drop table if exists {name}")
    delete(spark, f"{checkpoint_dir(spark)}/{name}")


def packed(docs: DataFrame, keep: list[str], **own: Column) -> DataFrame:
    """``kept``, a struct of the columns ``keep``, beside an operator's own columns: no names can clash."""
    inner = [F.col(f"`{c}`") for c in keep] or [F.lit(0).alias("none")]
    return docs.select(F.struct(*inner).alias("kept"), *[v.alias(k) for k, v in own.items()])


def unpacked(frame: DataFrame, keep: list[str], **added: Column) -> DataFrame:
    """The kept columns and the added ones. A kept column with an added one's name comes out as ``input_<name>``."""
    taken = {a.lower() for a in added} | {c.lower() for c in keep}
    out = []
    for c in keep:
        name = c
        if c.lower() in {a.lower() for a in added}:
            while name.lower() in taken:
                name = f"input_{name}"
            taken.add(name.lower())
        out.append(F.col("kept").getField(c).alias(name))
    return frame.select(*out, *[v.alias(k) for k, v in added.items()])


def release(spark: SparkSession) -> None:
    """Let the cleaner drop shuffle and checkpoint files that nothing refers to any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def give_back() -> None:
    """Return freed memory to the system: a worker that waits for its next task keeps what it has freed otherwise."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        pass


def trimmed(fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``fn`` for mapInArrow, giving memory back when a task ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from fn(batches)
        finally:
            give_back()

    return run


def text_of(name: str = "text") -> Column:
    """The text column with nulls read as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def byte_list(column: pa.Array) -> list[bytes]:
    """The UTF-8 bytes of a string column; nulls are empty."""
    return [b or b"" for b in pc.cast(column, pa.binary()).to_pylist()]


def map_arrow(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str) -> DataFrame:
    """Apply a batch-to-batch function."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield fn(batch)

    return df.mapInArrow(run, schema)


def read_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ``documents`` table."""
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
