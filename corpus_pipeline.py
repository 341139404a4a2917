"""Corpus pipeline over ``documents``.

quality: texts that the classifier rejects go. near duplicates: of every group of
documents linked at a similarity of 0.8 one stays. repeated passages: strings of
``suffix_dedup.PASSAGE`` bytes that start at more than one place are cut out. mixture: sources
are brought towards target weights within one epoch. pieces: what is left is
encoded with SentencePiece.

Defined results, beyond those of the operators: columns that documents lacks usually
pass through every stage but the last, whatever their names; a null text is empty
after the passages' stage; an empty table gives an empty result.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdrift.llm import common, mixing, pieces, pu_quality, suffix_dedup, superminhash

#: Share of the remaining tokens that the mixture takes.
MIX_SHARE = 0.95


def _carried(docs: DataFrame, *without: str) -> tuple[DataFrame, list[str]]:
    """The columns that a stage reads, and ``row``, a struct of all columns but ``without``: a stage's own names can't clash with those."""
    kept = [c for c in docs.columns if c not in without]
    return docs.select(*[F.col(c) for c in ("doc_id", "text", "lang", "source")], F.struct(*[F.col(f"`{c}`") for c in kept]).alias("row")), kept


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = pu_quality.learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return pu_quality.score_documents(_carried(docs)[0], model, keep=["row"]).where("predicted = 1").select("row.*")


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that repeat an id are one group, of which the row of least hash stays; rows without an id all stay."""
    kept = superminhash.near_duplicates(docs, percent=80).where("kept and doc_id is not null").select("doc_id").distinct()
    rows = _carried(docs)[0].select("doc_id", "row")
    named = rows.where("doc_id is not null")
    if named.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count():
        named = named.groupBy("doc_id").agg(F.min_by("row", F.xxhash64("row")).alias("row"))
    return named.join(kept, "doc_id", "left_semi").select("row.*").unionAll(rows.where("doc_id is null").select("row.*"))


def passage_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rows, kept = _carried(docs, "text", "n_chars")
    cut = suffix_dedup.remove_repeats(rows, suffix_dedup.PASSAGE, keep=["row"], as_text=True, gram=suffix_dedup.PASSAGE_GRAM)
    text = F.decode("kept_bytes", "UTF-8")
    new = {"text": text, "n_chars": F.length(text).cast("long")}
    return cut.select(*[F.col("row").getField(c).alias(c) if c in kept else new[c].alias(c) for c in docs.columns])


def mixture_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(_carried(docs)[0], budget_share=MIX_SHARE, epochs=1, keep=["row"]).select("row.*")


def piece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    coded = pieces.encode_documents(docs, keep=["doc_id", "lang", "source"])
    return coded.select(
        "doc_id",
        "lang",
        "source",
        F.size("piece_ids").cast("long").alias("n_tokens"),
        F.sha2(F.concat_ws(",", F.col("piece_ids").cast("array<string>")).cast("binary"), 256).alias("ids_sha256"),
        F.sha2(F.col("piece_text").cast("binary"), 256).alias("decoded_sha256"),
    )


STAGES = [
    ("quality", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("repeated_passages", passage_stage),
    ("mixture", mixture_stage),
    ("pieces", piece_stage),
]

#: Learning, signatures and tokens are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply the stages to ``documents``; each one's result is written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    root = f"{common.checkpoint_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    before = None
    for name, stage in STAGES:
        path = f"{root}/{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before:
            common.delete(spark, before)
        before = path
        pieces.release(spark)
        common.release(spark)
    return docs
