"""Graphs made from the given tables, and readers of public graph formats.

Edges are canonical: src < dst, distinct, no loops.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdrift.operators.ranks import global_rank


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table, pruned to the named columns."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def canonical(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Undirected distinct edges without loops."""
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    return edges.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).where("src <> dst").distinct()


def next_key(df: DataFrame, column: str) -> int:
    """One more than the largest key (0 for an empty table)."""
    top = df.agg(F.max(column)).first()[0]
    return 0 if top is None else top + 1


def cube_side(n: int) -> int:
    side = round(n ** (1 / 3))
    while side**3 > n:
        side -= 1
    while (side + 1) ** 3 <= n:
        side += 1
    return side


def cell_edges(cells: DataFrame, vid: Column, a: int, b: int, c: int) -> DataFrame:
    """Edges of a cell to its neighbours one step on along each axis: three filters, no join."""
    x, y, z = vid % a, F.expr(f"(vid div {a}) % {b}"), F.expr(f"vid div {a * b}")
    steps = [(x < a - 1, 1), (y < b - 1, a), (z < c - 1, a * b)]
    parts = [cells.where(ok).select(F.col("vid").alias("src"), (F.col("vid") + step).alias("dst")) for ok, step in steps]
    return parts[0].unionAll(parts[1]).unionAll(parts[2])


def lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A cube of cells numbered by the order keys."""
    orders = table(spark, sf_dir, "orders", "o_orderkey")
    side = cube_side(orders.count())
    cells = orders.select(F.col("o_orderkey").cast("long").alias("vid")).where(F.col("vid") < side**3)
    return cell_edges(cells, F.col("vid"), side, side, side)


def custsupp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and the suppliers of their orders' lines."""
    base = next_key(table(spark, sf_dir, "customer", "c_custkey"), "c_custkey")
    orders, lines = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey")
    joined = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.select(F.col("o_custkey").cast("long").alias("src"), (F.col("l_suppkey") + base).cast("long").alias("dst")).distinct()


def cop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers, orders and parts: who ordered, what is in it."""
    customers = next_key(table(spark, sf_dir, "customer", "c_custkey"), "c_custkey")
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    parts = customers + next_key(orders, "o_orderkey")
    placed = orders.select(F.col("o_custkey").cast("long").alias("src"), (F.col("o_orderkey") + customers).cast("long").alias("dst"))
    holds = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").select((F.col("l_orderkey") + customers).cast("long").alias("src"), (F.col("l_partkey") + parts).cast("long").alias("dst"))
    return placed.unionAll(holds).distinct()


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts in one order."""
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").distinct()
    a, b = lines.select("l_orderkey", F.col("l_partkey").cast("long").alias("src")), lines.select("l_orderkey", F.col("l_partkey").cast("long").alias("dst"))
    return a.join(b, "l_orderkey").where("src < dst").select("src", "dst").distinct()


def pagelinks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the targets of their links; targets are numbered in text order."""
    pages = table(spark, sf_dir, "pages", "page_id", "html")
    base = next_key(pages, "page_id")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target")).distinct()
    numbered = global_rank(links.select("target").distinct(), "target", name="t")
    return links.join(numbered, "target").select(F.col("page_id").cast("long").alias("src"), (F.col("t") + base).cast("long").alias("dst"))


def knn(spark: SparkSession, sf_dir: str, neighbours: int = 8, block: int = 1000) -> DataFrame:
    """Each vector's nearest by cosine, made undirected. Blocks meet blocks as matrix products."""
    vectors = table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    blocks = max(1, -(-vectors.count() // block))
    dealt = vectors.select(F.pmod("vec_id", F.lit(blocks)).cast("int").alias("b"), F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    pairs = dealt.select("*", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("o"))
    sides = pairs.select(F.col("b").alias("q"), F.col("o").alias("c"), "vec_id", "embedding", F.lit(0).alias("side")).unionAll(pairs.select(F.col("o").alias("q"), F.col("b").alias("c"), "vec_id", "embedding", F.lit(1).alias("side")))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        def side(k: int) -> tuple[np.ndarray, np.ndarray]:
            part = pdf[pdf.side == k]
            m = np.array(part.embedding.tolist(), np.float64).reshape(len(part), -1)
            return part.vec_id.to_numpy(), m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)

        (qi, qm), (ci, cm) = side(0), side(1)
        if not len(qi) or not len(ci):
            return pd.DataFrame({"src": [], "dst": [], "sim": []})
        sim = qm @ cm.T
        sim[qi[:, None] == ci[None, :]] = -2
        n = min(neighbours, len(ci))
        top = np.argpartition(-sim, n - 1, axis=1)[:, :n]
        return pd.DataFrame({"src": np.repeat(qi, n), "dst": ci[top].ravel(), "sim": np.take_along_axis(sim, top, 1).ravel()})

    near = sides.groupBy("q", "c").applyInPandas(best, "src long, dst long, sim double").where("sim > -2")
    ranked = near.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), "dst"))).where(F.col("r") <= neighbours)
    return canonical(ranked)


def interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, ts, src, dst: a user's event points at user (k mod users); loops stay."""
    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "props")
    users = max(1, table(spark, sf_dir, "events", "user_id").distinct().count())
    k = F.get_json_object("props", "$.k").cast("long")
    return events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").cast("long").alias("src"), F.pmod(k, F.lit(users)).alias("dst"))


def mentions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Directed arcs src, dst, weight of the mention stream, without loops."""
    return interactions(spark, sf_dir).where("src <> dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))


def calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The undirected ties of the stream with first and last call."""
    both = interactions(spark, sf_dir).where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "ts")
    return both.groupBy("src", "dst").agg(F.min("ts").alias("first_seen"), F.max("ts").alias("last_seen"))


def succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    """This event's user and the next event's: lead inside days, stitched over day borders."""
    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("day", F.to_date("ts"))
    inside = events.withColumn("next", F.lead("user_id").over(Window.partitionBy("day").orderBy("ts", "event_id"))).select("user_id", "next")
    # a row a day: bounded by the calendar
    ends = events.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    over = ends.select(F.col("last").alias("user_id"), F.lead("first").over(Window.orderBy("day")).alias("next"))
    return canonical(inside.unionAll(over).where("next is not null"), "user_id", "next")


GRAPHS = {"lattice": lattice, "knn": knn, "copurchase": copurchase, "custsupp": custsupp, "pagelinks": pagelinks, "cop": cop, "succession": succession}


def graph_from(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return GRAPHS[name](spark, sf_dir)


def read_edges(spark: SparkSession, path: str, format: str = "csv", sep: str = "\t") -> DataFrame:
    """Edge lists as delimited text (# comments), JSON lines or parquet, with a fixed schema."""
    if format == "csv":
        raw = spark.read.schema("src long, dst long").option("comment", "#").csv(path, sep=sep)
    else:
        raw = spark.read.schema("src long, dst long").format(format).load(path)
    return canonical(raw)
