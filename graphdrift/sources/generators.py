"""Synthetic graphs and growth: cubes, clustered power laws, forest fire, border attachment."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphdrift.functions.hashing import BURN, PICK, mix32, salt_of, threshold
from graphdrift.functions.lineage import cut
from graphdrift.operators import search
from graphdrift.operators.graph import symmetric, vertices_of
from graphdrift.operators.ranks import global_rank
from graphdrift.operators.replicas import fits
from graphdrift.sources.graphs import canonical, cell_edges


def lattice3d(spark: SparkSession, a: int, b: int, c: int, cells: DataFrame | None = None) -> DataFrame:
    """A cuboid of cells; 3abc - ab - bc - ca edges. ``cells`` (vid) are those there are; all, unless told."""
    cells = spark.range(a * b * c).withColumnRenamed("id", "vid") if cells is None else cells.where(F.col("vid") < a * b * c)
    return cell_edges(cells, F.col("vid"), a, b, c)


def powerlaw_clustered(spark: SparkSession, n: int, e: int, p: float = 0.1, seed: int = 0, chunk: int | None = None, vertices: DataFrame | None = None) -> DataFrame:
    """Growth by preferential attachment with triads.

    Newcomers come in rounds; all of a round pick from the endpoints that the round
    found (an endpoint's share is its degree). A pick after the first closes, with
    chance ``p``, a triad over the arc picked before it. ``chunk`` newcomers a round
    (default: as many as there are vertices already, so rounds number log n).
    ``vertices`` (vid) come in the order of their ids, and edges are between them.
    """
    if vertices is not None:
        grown = powerlaw_clustered(spark, n, e, p, seed, chunk)
        numbered = cut(global_rank(vertices.select("vid"), "vid"))
        at = lambda c: numbered.select(F.col("rank").alias(c), F.col("vid").alias(f"{c}_vid"))
        return canonical(grown.join(at("src"), "src").join(at("dst"), "dst"), "src_vid", "dst_vid")
    edges = cut(spark.range(e).select(F.col("id").alias("src"), F.lit(e).cast("long").alias("dst")))
    have = e + 1
    while have < n:
        size = min(n - have, chunk or have)
        ends = cut(global_rank(symmetric(edges), "src", "dst"))
        total = ends.count()
        new = spark.range(have, have + size).select(F.col("id").alias("v"), F.explode(F.sequence(F.lit(0), F.lit(e - 1))).alias("j"))
        new = new.withColumn("rank", F.pmod(mix32("v", salt_of(seed, PICK, 0, F.col("j"))), F.lit(total)))
        picked = new.join(ends, "rank").select("v", "j", F.col("src").alias("target"), F.col("dst").alias("beside"))
        before = F.lag("beside").over(Window.partitionBy("v").orderBy("j"))
        triad = (mix32("v", salt_of(seed, PICK, 1, F.col("j"))) < threshold(p)) & before.isNotNull()
        edges = cut(canonical(edges.unionAll(picked.select(F.col("v").alias("src"), F.when(triad, before).otherwise(F.col("target")).alias("dst")))))
        have += size
    return edges


def forest_fire(edges: DataFrame, newcomers: int, p: float = 0.35, depth: int = 3, seed: int = 0, first: int | None = None) -> DataFrame:
    """Edges of newcomers that burn outwards from an ambassador, all against the graph as it is.

    ``depth`` bounds the fire; a vertex catches by a coin of (newcomer, vertex).
    """
    spark = edges.sparkSession
    if fits(edges):
        if first is None:
            first = (edges.agg(F.max(F.greatest("src", "dst"))).first()[0] or 0) + 1
        return cut(search.fire_rows(edges, first, newcomers, p, depth, seed))
    sym = cut(symmetric(edges))
    known = cut(global_rank(vertices_of(edges), "vid"))
    n = known.count()
    first = (known.agg(F.max("vid")).first()[0] or 0) + 1 if first is None else first
    new = spark.range(first, first + newcomers).select(F.col("id").alias("w")).withColumn("rank", F.pmod(mix32("w", salt_of(seed, PICK)), F.lit(max(1, n))))
    burnt = cut(new.join(known, "rank").select("w", "vid"))
    front = burnt
    for _ in range(depth):
        reached = front.join(sym, front.vid == sym.src).select("w", F.col("dst").alias("vid")).distinct()
        coin = mix32(F.col("vid"), F.col("w") * 31 + salt_of(seed, BURN)) < threshold(p)
        front = cut(reached.where(coin).join(burnt, ["w", "vid"], "left_anti"))
        burnt = cut(burnt.unionAll(front))
    return burnt.select(F.least("w", "vid").alias("src"), F.greatest("w", "vid").alias("dst"))


def attach_border(edges: DataFrame, region: DataFrame, newcomers: int, links: int = 3, seed: int = 0, first: int | None = None) -> DataFrame:
    """Edges of newcomers to the live cells beside ``region`` (vid), chosen by degree."""
    spark = edges.sparkSession
    sym = symmetric(edges)
    inside = region.select(F.col("vid").alias("r")).distinct()
    border = sym.join(inside, sym.src == F.col("r"), "left_semi").select(F.col("dst").alias("vid")).distinct().join(inside, F.col("vid") == F.col("r"), "left_anti")
    ends = cut(global_rank(sym.join(border, sym.src == border.vid, "left_semi").select("src", "dst"), "src", "dst"))
    total = ends.count()
    first = edges.agg(F.max("dst")).first()[0] + 1 if first is None else first
    new = spark.range(first, first + newcomers).select(F.col("id").alias("v"), F.explode(F.sequence(F.lit(0), F.lit(links - 1))).alias("j"))
    new = new.withColumn("rank", F.pmod(mix32("v", salt_of(seed, PICK, 2, F.col("j"))), F.lit(max(1, total))))
    return canonical(new.join(ends.select("rank", F.col("src").alias("cell")), "rank"), "cell", "v")
