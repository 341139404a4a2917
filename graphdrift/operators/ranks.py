"""Global positions without a one-task window: range partitions, their counts, offsets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphdrift.functions.lineage import cut


def global_rank(df: DataFrame, *order: str | Column, name: str = "rank", partitions: int | None = None) -> DataFrame:
    """Add ``name``: 0-based position of each row in the given order (which should be total)."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keyed = df.select("*", *[(F.col(c) if isinstance(c, str) else c).alias(f"__o{i}") for i, c in enumerate(order)])
    keys = [f"__o{i}" for i in range(len(order))]
    dealt = cut(keyed.repartitionByRange(n, *keys).withColumn("__p", F.spark_partition_id()))
    # one row a partition: bounded by ``n``
    sizes = dealt.groupBy("__p").agg(F.count(F.lit(1)).alias("__n"))
    before = sizes.select("__p", (F.sum("__n").over(Window.orderBy("__p")) - F.col("__n")).alias("__before"))
    place = F.row_number().over(Window.partitionBy("__p").orderBy(*keys)) - 1
    return dealt.join(F.broadcast(before), "__p").withColumn(name, (F.col("__before") + place).cast("long")).drop("__p", "__before", *keys)
