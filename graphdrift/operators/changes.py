"""The change queue: ops wait, are put in order, and take effect between iterations."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphdrift import schemas
from graphdrift.operators.graph import vertices_of
from graphdrift.operators.initial import place_newcomers


def apply_changes(edges: DataFrame, vertices: DataFrame, changes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges and vertices after a batch.

    Ops count as if done by descending priority, then ascending seq. Of an edge or a
    vertex the last op decides; an edge also ends with the last deletion of either
    end that comes after its addition.
    """
    at = F.struct((-F.coalesce("priority", F.lit(0))).alias("p"), F.col("seq").alias("s"))
    ops = changes.withColumn("at", at)
    edge_ops = ops.where("op in ('add_edge', 'del_edge') and src <> dst").select("op", F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "at")
    last = edge_ops.groupBy("src", "dst").agg(F.max(F.struct("at", "op")).alias("l")).select("src", "dst", "l.at", "l.op")
    dead = ops.where("op = 'del_vertex'").groupBy(F.col("src").alias("vid")).agg(F.max("at").alias("died"))
    first = F.struct(F.lit(-(2**31)).cast("int").alias("p"), F.lit(-1).cast("long").alias("s"))
    old = edges.join(last.select("src", "dst"), ["src", "dst"], "left_anti").select("src", "dst", first.alias("at"))
    alive = old.unionByName(last.where("op = 'add_edge'").select("src", "dst", "at"))
    for side in ("src", "dst"):
        d = dead.select(F.col("vid").alias(side), "died")
        alive = alive.join(d, side, "left").where(F.col("died").isNull() | (F.col("died") < F.col("at"))).drop("died")
    new_edges = alive.select("src", "dst")
    vertex_ops = ops.where("op in ('add_vertex', 'del_vertex')").select(F.col("src").alias("vid"), "op", "at")
    implied = edge_ops.where("op = 'add_edge'").select(F.explode(F.array("src", "dst")).alias("vid"), F.lit("add_vertex").alias("op"), "at")
    final = vertex_ops.unionByName(implied).groupBy("vid").agg(F.max(F.struct("at", "op")).alias("l")).select("vid", "l.op")
    kept = vertices.select("vid").join(final.where("op = 'del_vertex'"), "vid", "left_anti")
    return new_edges, kept.unionAll(final.where("op = 'add_vertex'").select("vid")).distinct()


def reassign(assignment: DataFrame, vertices: DataFrame, k: int, strategy: str = "hash", seed: int = 0, edges: DataFrame | None = None) -> DataFrame:
    """Places for a changed vertex set: old ones stay, the gone go, newcomers are placed."""
    old = assignment.select("vid", "part").join(vertices, "vid", "left_semi")
    new = vertices.join(assignment, "vid", "left_anti")
    return old.unionAll(place_newcomers(new, k, strategy, seed, edges, old))


@dataclass
class ChangeQueue:
    """Buffers changes; ``drain`` applies them every ``every_n`` supersteps unless frozen."""

    spark: SparkSession
    every_n: int = 1
    frozen: bool = False
    waiting: DataFrame | None = None

    def push(self, changes: DataFrame) -> None:
        changes = changes.select(*[c.split()[0] for c in schemas.CHANGES.split(", ")])
        self.waiting = changes if self.waiting is None else self.waiting.unionByName(changes)

    def drain(self, superstep: int, edges: DataFrame, vertices: DataFrame) -> tuple[DataFrame, DataFrame, bool]:
        if self.waiting is None or self.frozen or superstep % self.every_n:
            return edges, vertices, False
        out = apply_changes(edges, vertices, self.waiting)
        self.waiting = None
        return *out, True


def isolated(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Vertices without an edge."""
    return vertices.join(vertices_of(edges), "vid", "left_anti")
