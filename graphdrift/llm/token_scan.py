"""Token counts of documents in flat token files without an index.

A flat file is a run of fixed-width token ids in which an end-of-document id
closes every document. Files are read as fixed-size blocks that know nothing of
document borders. Each block is searched for the separator with one vector
comparison and becomes a summary (tokens, separators, tokens before the first and
after the last). A prefix scan over the summaries, first inside groups of blocks
and then over the groups, tells every block how many tokens of an unfinished
document reach into it and how many documents ended before it; with that each
block states its documents' lengths.

Defined results: null text is empty and counts 0 tokens; a file's tokens after
its last separator form an unterminated document if there are any; empty blocks
and files give nothing; repeated rows are documents of their own; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from urllib.parse import unquote

import numpy as np
import pyarrow as pa
import pyarrow.fs as pa_fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdrift.llm import common, pieces

#: Tokens of a block.
BLOCK = 1 << 16
#: Blocks that one window of the scan's first level holds.
GROUP = 1 << 12
EOD = 2  # the model's end id; encoding a text never yields it


def flat_files(docs: DataFrame, model: str | None = None, block: int = BLOCK) -> DataFrame:
    """Tokenise documents into flat files, one a task: file, block, data (uint16), and rows with
    block null that list doc_ids in file order (first, ids)."""
    common.tune(docs.sparkSession)
    model = model or pieces.default_model()
    names = ["file", "block", "data", "first", "ids"]
    kinds = [pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.list_(pa.int64())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, file = pieces.ChunkTable(model), TaskContext.get().partitionId()
        end = np.array([EOD], "<u2").tobytes()
        held, at, first = bytearray(), 0, 0
        row = lambda *x: pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(x, kinds)], names=names)
        for batch in batches:
            ids = batch.column(0).to_pylist()
            for coded in table.encode_all(batch.column(1).to_pylist()):
                held += np.frombuffer(coded, "<i4").astype("<u2").tobytes() + end
                while len(held) >= 2 * block:
                    yield row(file, at, bytes(held[: 2 * block]), None, None)
                    del held[: 2 * block]
                    at += 1
            yield row(file, None, None, first, ids)
            first += len(ids)
        if held:
            yield row(file, at, bytes(held), None, None)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_of().alias("text")).mapInArrow(run, "file long, block long, data binary, first long, ids array<long>")


def read_token_files(spark: SparkSession, path: str, width: int = 2, block: int = BLOCK, whole_bytes: int = 1 << 28, span_blocks: int = 256) -> DataFrame:
    """Blocks of binary token files of any size: file, block, data.

    Files up to ``whole_bytes`` are read by Spark as one value. Larger ones are only
    listed by Spark; spans of ``span_blocks`` blocks are then read as byte ranges through
    pyarrow's file systems, so no value holds more than a block.
    """
    step = width * block
    listed = spark.read.format("binaryFile").load(path)
    small = listed.where(F.col("length") <= whole_bytes).select(F.xxhash64("path").alias("file"), "content")
    cut = F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.octet_length("content") - 1) / step).cast("int")))
    pieces_ = small.select("file", "content", F.explode(cut).alias("block")).select("file", F.col("block").cast("long").alias("block"), F.expr(f"substring(content, block * {step} + 1, {step})").alias("data"))
    span = step * span_blocks
    large = listed.where(F.col("length") > whole_bytes).select(F.xxhash64("path").alias("file"), "path", "length")
    ranges = large.select("file", "path", F.explode(F.sequence(F.lit(0), F.expr(f"(length - 1) div {span}"))).alias("span"))

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, where, k in zip(*(batch.column(c).to_pylist() for c in range(3))):
                uri = where if "://" in where else where.replace(":/", ":///", 1)  # Hadoop writes file:/x
                system, at = pa_fs.FileSystem.from_uri(unquote(uri))
                with system.open_input_file(at) as source:
                    source.seek(k * span)
                    for n in range(span_blocks):
                        data = source.read(step)
                        if not data:
                            break
                        yield pa.RecordBatch.from_arrays([pa.array([file], pa.int64()), pa.array([k * span_blocks + n], pa.int64()), pa.array([data], pa.binary())], names=["file", "block", "data"])

    return pieces_.unionAll(ranges.repartition("file", "span").mapInArrow(read, "file long, block long, data binary"))


def _summaries(blocks: DataFrame, eod: int, width: int) -> DataFrame:
    """file, block, n, k, head, tail, inner: what a block says by itself."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for data in batch.column(2).to_pylist():
                ids = np.frombuffer(data, f"<u{width}")
                ends = np.flatnonzero(ids == eod)
                if len(ends):
                    out.append((len(ids), len(ends), int(ends[0]), len(ids) - int(ends[-1]) - 1, np.diff(ends) - 1))
                else:
                    out.append((len(ids), 0, len(ids), len(ids), np.zeros(0, np.int64)))
            columns = [pa.array([o[k] for o in out], pa.int64()) for k in range(4)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns, pa.array([o[4] for o in out], pa.list_(pa.int64()))], names=["file", "block", "n", "k", "head", "tail", "inner"])

    return blocks.select("file", "block", "data").mapInArrow(run, "file long, block long, n long, k long, head long, tail long, inner array<long>")


def _scan(frame: DataFrame, part: list[str], order: str) -> DataFrame:
    """Add, from the rows before: ``carry`` (tail tokens since a separator), ``docs`` (separators), ``met`` (any)."""
    w = Window.partitionBy(*part).orderBy(order)
    frame = frame.withColumn("turn", F.sum((F.col("k") > 0).cast("long")).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    run = Window.partitionBy(*part, "turn").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    frame = frame.withColumn("open", F.sum("tail").over(run))
    carry, docs = F.coalesce(F.lag("open").over(w), F.lit(0)), F.coalesce(F.sum("k").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return frame.withColumn("carry", carry).withColumn("docs", docs).withColumn("met", F.col("docs") > 0)


def document_lengths(blocks: DataFrame, eod: int = EOD, width: int = 2, group: int = GROUP) -> DataFrame:
    """file, ordinal, n_tokens, terminated of every document in the blocks (file, block, data)."""
    common.tune(blocks.sparkSession)
    own = common.cut(_summaries(blocks.where("block is not null"), eod, width)).withColumn("grp", F.expr(f"block div {group}"))
    inside = _scan(own, ["file", "grp"], "block")
    last = inside.groupBy("file", "grp").agg(F.sum("k").alias("k"), F.max_by("open", "block").alias("tail"))
    over = _scan(last, ["file"], "grp").select("file", "grp", F.col("carry").alias("g_carry"), F.col("docs").alias("g_docs"))
    top = own.groupBy("file").agg(F.max("block").alias("last_block"))
    told = inside.join(over, ["file", "grp"]).join(top, "file")
    told = told.withColumn("into", F.col("carry") + F.when(F.col("met"), F.lit(0)).otherwise(F.col("g_carry"))).withColumn("base", F.col("docs") + F.col("g_docs"))
    whole = F.when(F.col("k") > 0, F.concat(F.array(F.col("into") + F.col("head")), F.col("inner"))).otherwise(F.array().cast("array<bigint>"))
    rest = F.when(F.col("k") > 0, F.col("tail")).otherwise(F.col("into") + F.col("n"))
    ended = told.select("file", "base", F.posexplode(whole).alias("p", "n_tokens")).select("file", (F.col("base") + F.col("p")).alias("ordinal"), "n_tokens", F.lit(True).alias("terminated"))
    loose = told.where(F.col("block") == F.col("last_block")).select("file", (F.col("base") + F.col("k")).alias("ordinal"), rest.alias("n_tokens"), F.lit(False).alias("terminated")).where("n_tokens > 0")
    return ended.unionAll(loose)


def token_counts(docs: DataFrame) -> DataFrame:
    """doc_id and n_tokens of every row, by way of flat files."""
    files = common.cut(flat_files(docs))
    names = files.where("block is null").select("file", "first", F.posexplode("ids").alias("p", "doc_id")).select("file", (F.col("first") + F.col("p")).alias("ordinal"), "doc_id")
    return document_lengths(files).join(names, ["file", "ordinal"]).select("doc_id", "n_tokens", "terminated")
