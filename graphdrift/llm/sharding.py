"""Balanced range shards from sampled splitters.

Records are ordered by a composite key (digest of the text, digest of the id), so
copies of a text are neighbours and a hot text can still be divided inside its
group. A size-weighted sample of keys (bounded, by exponential ranks) gives the
quantile boundaries of many small ranges; ranges that come out overfull are
sampled again and subdivided. Exact range totals then give each range its offset
on the line of bytes, and a record's shard is where its middle lies on that line:
shard sizes differ by no more than about one record.

Defined results: null text has size 1; null ids sort first and are ordered like
any other; repeated rows are interchangeable; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

import bisect

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdrift.llm import common

KEY = ["k1", "k2"]


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32 and the two-part key; the text itself goes no further."""
    raw = common.text_of().cast("binary")
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(raw) + 1).cast("long").alias("size"),
        F.crc32(raw).alias("text_crc32"),
        F.md5(raw).alias("k1"),
        F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")).alias("k2"),
    )


def weighted_sample(records: DataFrame, most: int, total: int) -> list[tuple[str, str]]:
    """About ``most`` keys, drawn without replacement with chances proportional to size.

    Ranks are exponential with rate size, so about ``most`` of them lie below
    most / total; only those leave the executors, however many tasks there are.
    """
    draw = (F.pmod(F.xxhash64(*KEY), F.lit(2**52)) + 1) / F.lit(float(2**52 + 1))
    below = records.where(-F.log(draw) / F.col("size") <= F.lit(most / max(1, total)))
    return [(r["k1"], r["k2"]) for r in below.select(*KEY).distinct().collect()]


def boundaries(sample: list[tuple[str, str]], ranges: int) -> list[tuple[str, str]]:
    """Upper-open quantile boundaries of a key sample; at most ``ranges - 1`` of them."""
    keys = sorted(sample)
    return sorted({keys[i * len(keys) // ranges] for i in range(1, ranges)}) if keys else []


def with_range(records: DataFrame, bounds: list[tuple[str, str]]) -> DataFrame:
    """Add the number of the key range that a record falls into."""
    joined = [a + b for a, b in bounds]

    @F.pandas_udf("int")
    def find(key: pd.Series) -> pd.Series:
        return pd.Series(np.fromiter((bisect.bisect_right(joined, k) for k in key), np.int32, len(key)))

    return records.withColumn("range", find(F.concat(*KEY)))


def subdivided(records: DataFrame, bounds: list[tuple[str, str]], ranges: int, per_range: int, overfull: float) -> list[tuple[str, str]]:
    """Add boundaries inside the ranges that hold over ``overfull`` times the mean size."""
    totals = {r["range"]: r["size"] for r in with_range(records, bounds).groupBy("range").agg(F.sum("size").alias("size")).collect()}
    mean = sum(totals.values()) / max(1, ranges)
    big = [k for k, v in totals.items() if v > overfull * mean]
    if not big:
        return bounds
    inside = with_range(records, bounds).where(F.col("range").isin(big))
    more = [boundaries(x, int(np.ceil(totals[k] / mean))) for k in big if (x := weighted_sample(inside.where(F.col("range") == k), int(per_range * np.ceil(totals[k] / mean)), totals[k]))]
    return sorted({*bounds, *(b for x in more for b in x)})


def shard_records(docs: DataFrame, shards: int = 16, per_range: int = 32, least_ranges: int = 128, range_bytes: int = 1 << 30, most_ranges: int = 8192, overfull: float = 2.0) -> DataFrame:
    """Place every row: doc_id, size, text_crc32, shard, slot.

    Ranges number ``total / range_bytes`` within [least_ranges, most_ranges]; the
    splitters on the driver number no more than ``most_ranges``.
    """
    common.tune(docs.sparkSession)
    records = common.cut(keyed(docs))
    total = records.agg(F.sum("size")).first()[0] or 0
    ranges = int(min(most_ranges, max(least_ranges, total // range_bytes)))
    bounds = boundaries(weighted_sample(records, ranges * per_range, total), ranges)
    bounds = subdivided(records, bounds, ranges, per_range, overfull)
    records = with_range(records, bounds)
    # one row a range: bounded by the number of splitters
    sums = records.groupBy("range").agg(F.sum("size").alias("n"))
    before = sums.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("start"))
    line = records.join(F.broadcast(before), "range")
    order = Window.partitionBy("range").orderBy("k1", "k2", "doc_id")
    line = line.withColumn("upto", F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) + F.col("start"))
    line = line.withColumn("shard", F.least(F.lit(shards - 1), F.floor(F.expr(f"({shards} * (2 * upto - size)) div {max(1, 2 * total)}"))).cast("int")) if total else line.withColumn("shard", F.lit(0))
    within = Window.partitionBy("range", "shard").orderBy("k1", "k2", "doc_id")
    line = common.cut(line.withColumn("nth", F.row_number().over(within).cast("long")).select("doc_id", "size", "text_crc32", "range", "shard", "nth"))
    # pieces: at most one row a range and shard
    pieces = line.groupBy("shard", "range").agg(F.count(F.lit(1)).alias("n"))
    ahead = pieces.select("shard", "range", (F.sum("n").over(Window.partitionBy("shard").orderBy("range")) - F.col("n")).alias("ahead"))
    return line.join(F.broadcast(ahead), ["shard", "range"]).select("doc_id", "size", "text_crc32", "shard", (F.col("ahead") + F.col("nth") - 1).alias("slot"))


def shard_documents(docs: DataFrame, shards: int = 16) -> DataFrame:
    """The placement under the law of near-equal bytes."""
    none = F.lit(None).cast("int")
    return shard_records(docs, shards).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", none.alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, shards: int = 16) -> None:
    """Write the documents' rows into one folder a shard, in slot order."""
    at = shard_records(docs, shards).select("doc_id", "shard", "slot").dropDuplicates(["doc_id"])
    docs.join(at, "doc_id").repartition(shards, "shard").sortWithinPartitions("shard", "slot").write.partitionBy("shard").mode("overwrite").parquet(path)
