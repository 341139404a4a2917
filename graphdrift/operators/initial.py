"""Initial placements: modulo and mixed hash, balanced random, streaming greedy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdrift.functions.hashing import PLACE, TIE, mix32, salt_of
from graphdrift.functions.lineage import cut
from graphdrift.operators.graph import symmetric
from graphdrift.operators.ranks import global_rank
from graphdrift.operators.replicas import EDGE, VERTEX, Graph, ids_of, packed, streams, unpacked

#: Vertices of a stream whose neighbours are listed at once.
STRETCH = 100_000


def assign_hash(vertices: DataFrame, k: int, mixed: bool = True, seed: int = 0) -> DataFrame:
    """Hash of the id modulo k (mixed), or the id modulo k. No shuffle."""
    h = mix32("vid", salt_of(seed, PLACE)) if mixed else F.col("vid")
    return vertices.select("vid", F.pmod(h, F.lit(k)).cast("int").alias("part"))


def assign_random(vertices: DataFrame, k: int, seed: int = 0) -> DataFrame:
    """Pseudorandom and balanced: the rank by hash, modulo k; loads differ by one at most."""
    ranked = global_rank(vertices.select("vid"), mix32("vid", salt_of(seed, PLACE)), "vid")
    return ranked.select("vid", F.pmod("rank", F.lit(k)).cast("int").alias("part"))


def _place(rule: str, load: list[int], near: list[int], cap: int) -> int:
    """The part for one vertex of a stream. Full parts are taken only when all are full; ties go to the
    least loaded, then the lowest."""
    full, best, top, least = min(load) >= cap, -1, 0, 0
    for i, here in enumerate(load):
        if here < cap or full:
            score = near[i] * (cap - here) if rule == "dgr" else near[i] - here if rule == "mnn" else -near[i]
            if best < 0 or score > top or (score == top and here < least):
                best, top, least = i, score, here
    return best


def stream_exact(edges: DataFrame, vertices: DataFrame, k: int, rule: str = "dgr", cap: int | None = None) -> DataFrame:
    """One vertex after another in id order, by one task, over arrays, for graphs that fit in it (see ``replicas``).

    dgr: most placed neighbours, weighted by the share of free room. mnn: fewest
    members that aren't neighbours. mnn_literal: fewest placed neighbours.
    """
    n, size = vertices.count(), edges.count()
    cap = -(-n // k) if cap is None else cap
    pairs = packed(edges.select(F.col("src").cast("long"), F.col("dst").cast("long")), [0], EDGE)
    ids = packed(vertices.select(F.col("vid").cast("long"), F.lit(0).cast("long")), [0], VERTEX)

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        arcs, filled, found = np.empty(2 * size, np.uint64), 0, [np.zeros(0, np.int64)]
        for batch in batches:
            for kind, rows in unpacked(batch):
                if kind == EDGE:
                    arcs[filled : filled + len(rows)], arcs[size + filled : size + filled + len(rows)] = rows[:, 0], rows[:, 1]
                    filled += len(rows)
                else:
                    found.append(rows[:, 0].copy())
        streamed = np.sort(np.concatenate(found))
        graph = Graph(np.union1d(streamed, ids_of(arcs)), arcs)
        del arcs
        took = np.isin(graph.vid, streamed, assume_unique=True)
        place, load = [-1] * len(took), [0] * k
        for a in range(0, len(took), STRETCH):
            b = min(len(took), a + STRETCH)
            first = graph.first[a : b + 1] - graph.first[a]
            near_to = graph.near_to[graph.first[a] : graph.first[b]]
            # only those before it can be placed
            before = near_to < np.repeat(np.arange(a, b), np.diff(first))
            ends = np.concatenate([[0], np.cumsum(before)])[first].tolist()
            earlier = near_to[before].tolist()
            for v, on in zip(range(a, b), took[a:b].tolist()):
                if on:
                    near = [0] * k
                    for x in earlier[ends[v - a] : ends[v - a + 1]]:
                        if place[x] >= 0:
                            near[place[x]] += 1
                    place[v] = p = _place(rule, load, near, cap)
                    load[p] += 1
            part = np.array(place[a:b], np.int32)[took[a:b]]
            yield pa.RecordBatch.from_arrays([pa.array(graph.vid[a:b][took[a:b]]), pa.array(part)], names=["vid", "part"])

    return pairs.unionAll(ids).repartition(1).mapInArrow(fold, "vid long, part int")


def stream_chunked(edges: DataFrame, vertices: DataFrame, k: int, rule: str = "dgr", chunk: int = 1000, cap: int | None = None) -> DataFrame:
    """The same rule for ``chunk`` vertices at once against the state the last chunk left.

    With chunk 1 it is the exact stream. Inside a chunk a part takes vertices up to
    its room by score; what is over goes to parts with room, least loaded first.
    Small graphs are one task's work instead of several jobs a chunk.
    """
    n = vertices.count()
    cap = -(-n // k) if cap is None else cap
    if streams(edges):
        return _chunked_in_a_task(edges, vertices, k, rule, chunk, cap)
    spark = vertices.sparkSession
    ranked = cut(global_rank(vertices.select("vid"), "vid"))
    sym = symmetric(edges).persist()
    placed = spark.createDataFrame([], "vid long, part int")
    parts = spark.range(k).select(F.col("id").cast("int").alias("part"))
    for lo in range(0, n, chunk):
        now = ranked.where((F.col("rank") >= lo) & (F.col("rank") < lo + chunk)).select("vid", "rank")
        # k rows
        load = parts.join(placed.groupBy("part").agg(F.count(F.lit(1)).alias("l")), "part", "left").select("part", F.coalesce("l", F.lit(0)).alias("load"))
        near = now.join(sym, now.vid == sym.src).join(placed.withColumnRenamed("vid", "dst"), "dst").groupBy("vid", "part").agg(F.count(F.lit(1)).alias("near"))
        every = now.join(F.broadcast(load)).join(near, ["vid", "part"], "left").withColumn("near", F.coalesce("near", F.lit(0)))
        score = {"dgr": F.col("near") * (cap - F.col("load")), "mnn": F.col("near") - F.col("load")}.get(rule, -F.col("near"))
        best = every.groupBy("vid", "rank").agg(F.max(F.struct((F.col("load") < cap).alias("free"), score.alias("score"), (-F.col("load")).alias("l"), (-F.col("part")).alias("p"))).alias("b"))
        best = best.select("vid", "rank", (-F.col("b.p")).alias("part"), F.col("b.score").alias("score"))
        order = F.row_number().over(Window.partitionBy("part").orderBy(F.desc("score"), "rank"))
        told = cut(best.join(F.broadcast(load), "part").withColumn("ok", (order <= cap - F.col("load")) | (F.lit(chunk) == 1)))
        fits = told.where("ok").select("vid", "part")
        over = told.where(~F.col("ok")).select("vid")
        if over.limit(1).count():
            after = parts.join(placed.unionAll(fits).groupBy("part").agg(F.count(F.lit(1)).alias("l")), "part", "left").select("part", F.greatest(F.lit(0), cap - F.coalesce("l", F.lit(0))).alias("free"))
            # free places in order of parts; at most ``chunk`` are needed
            spots = after.select("part", F.explode(F.sequence(F.lit(1).cast("long"), F.least(F.col("free"), F.lit(chunk).cast("long")))).alias("i")).where("i between 1 and free").select("part", F.row_number().over(Window.orderBy("i", "part")).alias("n"))
            rest = over.select("vid", F.row_number().over(Window.orderBy("vid")).alias("n"))
            fits = fits.unionAll(rest.join(spots, "n", "left").select("vid", F.coalesce("part", F.pmod("vid", F.lit(k)).cast("int")).alias("part")))
        placed = cut(placed.unionAll(fits))
    sym.unpersist()
    return placed


def _chunked_in_a_task(edges: DataFrame, vertices: DataFrame, k: int, rule: str, chunk: int, cap: int) -> DataFrame:
    """``stream_chunked`` over arrays of one chunk after another."""
    lists = symmetric(edges).groupBy(F.col("src").alias("vid")).agg(F.collect_list("dst").alias("nbrs"))
    stream = vertices.select("vid").join(lists, "vid", "left").repartition(1).sortWithinPartitions("vid")

    def fold(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        place: dict[int, int] = {}
        load = np.zeros(k, np.int64)
        ids: list[int] = []
        nears: list[np.ndarray] = []

        def placed() -> pd.DataFrame:
            nonlocal load
            vid, near = np.array(ids, np.int64), np.array(nears).reshape(-1, k)
            score = {"dgr": near * (cap - load), "mnn": near - load}.get(rule, -near)
            # the least loaded first, then the lowest; full parts only when all are full
            parts = np.lexsort((np.arange(k), load))
            if (load < cap).any():
                parts = parts[load[parts] < cap]
            part = parts[score[:, parts].argmax(axis=1)]
            own = score[np.arange(len(vid)), part]
            order = np.lexsort((np.arange(len(vid)), -own, part))
            begin = np.searchsorted(part[order], np.arange(k))
            turn = np.empty(len(vid), np.int64)
            turn[order] = np.arange(len(vid)) - begin[part[order]]
            over = np.flatnonzero((turn >= (cap - load)[part]) & (chunk > 1))
            stay = np.ones(len(vid), bool)
            stay[over] = False
            load = load + np.bincount(part[stay], minlength=k)
            if len(over):
                free = np.minimum(np.maximum(0, cap - load), chunk)
                spots = np.repeat(np.arange(k), free)
                spots = spots[np.lexsort((spots, np.arange(len(spots)) - np.repeat(np.cumsum(free) - free, free)))][: len(over)]
                part[over] = np.concatenate([spots, vid[over[len(spots) :]] % k])
                load = load + np.bincount(part[over], minlength=k)
            place.update(zip(ids, part.tolist()))
            ids.clear()
            nears.clear()
            return pd.DataFrame({"vid": vid, "part": part.astype(np.int32)})

        for pdf in frames:
            for v, nbrs in zip(pdf.vid.tolist(), pdf.nbrs):
                near = [0] * k
                for x in nbrs.tolist() if nbrs is not None else ():
                    p = place.get(x)
                    if p is not None:
                        near[p] += 1
                ids.append(v)
                nears.append(np.array(near, np.int64))
                if len(ids) == chunk:
                    yield placed()
        if ids:
            yield placed()

    return cut(stream.mapInPandas(fold, "vid long, part int"))


def place_newcomers(vids: DataFrame, k: int, strategy: str = "hash", seed: int = 0, edges: DataFrame | None = None, assignment: DataFrame | None = None, cap: int | None = None) -> DataFrame:
    """Parts of vertices that the graph hasn't seen: hash, random, or greedy by their placed neighbours."""
    if strategy == "hash":
        return assign_hash(vids, k, True, seed)
    if strategy == "random":
        return assign_random(vids, k, seed)
    sym = symmetric(edges)
    load = assignment.groupBy("part").agg(F.count(F.lit(1)).alias("load"))
    cap = -(-assignment.count() * 11 // (10 * k)) + 1 if cap is None else cap
    near = vids.join(sym, vids.vid == sym.src).join(assignment.withColumnRenamed("vid", "dst"), "dst").groupBy("vid", "part").agg(F.count(F.lit(1)).alias("near"))
    score = F.col("near") * (cap - F.col("load"))
    best = near.join(F.broadcast(load), "part").groupBy("vid").agg(F.max(F.struct(score.alias("s"), mix32("vid", salt_of(seed, TIE, 0, F.col("part"))).alias("t"), "part")).alias("b"))
    fallback = F.pmod(mix32("vid", salt_of(seed, PLACE)), F.lit(k)).cast("int")
    return vids.join(best, "vid", "left").select("vid", F.coalesce(F.col("b.part"), fallback).alias("part"))
