"""Frames of a graph and its placement."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def symmetric(edges: DataFrame) -> DataFrame:
    """Both directions of every edge; one scan."""
    return edges.select(F.explode(F.array(F.struct(F.col("src"), F.col("dst")), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))).alias("e")).select("e.src", "e.dst")


def vertices_of(edges: DataFrame) -> DataFrame:
    """Distinct end points, as vid."""
    return edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()


def localise(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """Edges with the places of both ends: src, dst, src_part, dst_part."""
    a = assignment.select(F.col("vid").alias("src"), F.col("part").alias("src_part"))
    b = assignment.select(F.col("vid").alias("dst"), F.col("part").alias("dst_part"))
    return edges.join(a, "src").join(b, "dst").select("src", "dst", "src_part", "dst_part")


def propagate_moves(local: DataFrame, moves: DataFrame) -> DataFrame:
    """Localised edges after moves (vid, to_part): neighbours learn the new places."""
    a = moves.select(F.col("vid").alias("src"), F.col("to_part").alias("__a"))
    b = moves.select(F.col("vid").alias("dst"), F.col("to_part").alias("__b"))
    out = local.join(a, "src", "left").join(b, "dst", "left")
    return out.select("src", "dst", F.coalesce("__a", "src_part").alias("src_part"), F.coalesce("__b", "dst_part").alias("dst_part"))


@dataclass
class GraphState:
    """Canonical edges and the place of every vertex."""

    edges: DataFrame
    assignment: DataFrame

    def validate(self, k: int) -> None:
        """The partitions are a disjoint cover."""
        r = self.assignment.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("vid").alias("d"), F.min("part").alias("lo"), F.max("part").alias("hi")).first()
        if r["n"] != r["d"] or (r["n"] and not 0 <= r["lo"] <= r["hi"] < k):
            raise ValueError(f"not a partitioning: {r}")


def locate(assignment: DataFrame, vids: DataFrame) -> DataFrame:
    """vid and its present part (null for an unknown vertex)."""
    return vids.select("vid").join(assignment.select("vid", "part"), "vid", "left")
