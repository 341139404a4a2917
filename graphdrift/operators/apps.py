"""Analyses that run on the graph: influence, cliques, diameter, tissue, ranks, components."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphdrift.functions.lineage import cut, forget
from graphdrift.operators import search
from graphdrift.operators.graph import symmetric, vertices_of
from graphdrift.operators.replicas import fits

#: Fixed-point units of a share of influence or rank: integer sums don't depend on order.
UNIT = 1_000_000_000


def influence(arcs: DataFrame, p: float = 0.5, iterations: int = 5) -> DataFrame:
    """vid, influence: what followers pass on, inf(x) = sum over followers f of (1 + p inf(f)) / outdeg(f).

    Arcs point from follower to followed. Shares are summed in fixed point.
    """
    out = arcs.groupBy("src").agg(F.count(F.lit(1)).alias("out"))
    arcs = arcs.select("src", "dst").join(out, "src").persist()
    rank = vertices_of(arcs).select("vid", F.lit(0).cast("long").alias("i"))
    for _ in range(iterations):
        share = F.floor((F.lit(UNIT) + F.lit(p) * F.col("i")) / F.col("out")).cast("long")
        got = arcs.join(rank.withColumnRenamed("vid", "src"), "src").select("dst", share.alias("s")).groupBy("dst").agg(F.sum("s").alias("s"))
        rank = cut(rank.join(got, rank.vid == got.dst, "left").select("vid", F.coalesce("s", F.lit(0)).alias("i")))
    arcs.unpersist()
    return rank.select("vid", F.round(F.col("i") / UNIT, 6).alias("influence"))


def pagerank(arcs: DataFrame, damping: float = 0.85, iterations: int = 3) -> DataFrame:
    """vid, rank (mean 1): dangling mass is dropped."""
    out = arcs.groupBy("src").agg(F.count(F.lit(1)).alias("out"))
    arcs = arcs.select("src", "dst").join(out, "src").persist()
    rank = vertices_of(arcs).select("vid", F.lit(UNIT).cast("long").alias("r"))
    for _ in range(iterations):
        got = arcs.join(rank.withColumnRenamed("vid", "src"), "src").select("dst", F.expr("r div out").alias("s")).groupBy("dst").agg(F.sum("s").alias("s"))
        new = F.floor(F.lit((1 - damping) * UNIT) + F.lit(damping) * F.coalesce("s", F.lit(0))).cast("long")
        rank = cut(rank.join(got, rank.vid == got.dst, "left").select("vid", new.alias("r")))
    arcs.unpersist()
    return rank.select("vid", F.round(F.col("r") / UNIT, 6).alias("rank"))


def components(edges: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """vid, component: least vertex reachable, by star contraction."""
    now, seen = cut(edges.select(F.greatest("src", "dst").alias("v"), F.least("src", "dst").alias("u")).distinct()), None
    while True:
        state = now.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("v", "u").cast("decimal(20,0)")).alias("h")).first()
        if state == seen or not state["n"]:
            break
        seen = state
        both = now.unionAll(now.select(F.col("u").alias("v"), F.col("v").alias("u")))
        least = both.groupBy("v").agg(F.min("u").alias("m")).select("v", F.least("v", "m").alias("m"))
        large = both.join(least, "v").where("u > v").select(F.col("u").alias("v"), F.col("m").alias("u")).distinct()
        m = large.groupBy("v").agg(F.min("u").alias("m"))
        small = large.join(m, "v").select(F.explode(F.array(F.struct(F.col("u").alias("v"), F.col("m").alias("u")), F.struct(F.col("v"), F.col("m").alias("u")))).alias("e"))
        now = cut(small.select("e.*").where("v <> u").distinct())
    vertices = vertices_of(edges) if vertices is None else vertices
    return vertices.join(now, vertices.vid == now.v, "left").select("vid", F.coalesce("u", "vid").alias("component"))


def max_cliques(edges: DataFrame, ordered: bool = False) -> DataFrame:
    """vid, size, members: each vertex's largest verified clique, in two supersteps.

    First every vertex sends its neighbour list to its neighbours. Then for each
    neighbour j, vertex i holds the list of common neighbours with i and j
    themselves; a list that comes from all its other members is a clique. Where
    none is, the best is an edge (lowest neighbour), or the vertex alone. ``ordered``
    asks higher neighbours only and lists no member below itself, so a clique is found
    once, at its lowest member; neighbours send whole lists all the same, or the lists of
    a clique's members couldn't agree.
    Of equally large cliques the one with the lowest members is given.
    """
    arcs = edges.select("src", "dst") if ordered else symmetric(edges)
    lists = symmetric(edges).groupBy(F.col("src").alias("vid")).agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))
    sent = arcs.join(lists.select(F.col("vid").alias("dst"), F.col("nbrs").alias("theirs")), "dst")
    own = F.filter("nbrs", lambda x: x > F.col("src")) if ordered else F.col("nbrs")
    held = sent.join(lists.withColumnRenamed("vid", "src"), "src")
    common = F.array_intersect(own, "theirs")
    closed = F.array_sort(F.array_union(common, F.array("src", "dst")))
    rows = held.select(F.col("src").alias("vid"), closed.alias("members"))
    times = rows.groupBy("vid", "members").agg(F.count(F.lit(1)).alias("n"))
    found = times.where(F.col("n") == F.size("members") - 1)
    edge = arcs.groupBy(F.col("src").alias("vid")).agg(F.min("dst").alias("d")).select("vid", F.array_sort(F.array("vid", "d")).alias("members"))
    alone = vertices_of(edges).select("vid", F.array("vid").alias("members"))
    every = found.select("vid", "members").unionByName(edge).unionByName(alone)
    best = every.groupBy("vid").agg(F.min(F.struct((-F.size("members")).alias("size"), "members")).alias("b"))
    return best.select("vid", F.size("b.members").alias("size"), F.concat_ws(",", F.col("b.members").cast("array<string>")).alias("members"))


def max_cliques_exact(edges: DataFrame) -> DataFrame:
    """vid, size: exact maximum clique through each vertex, by search in its neighbourhood (small graphs)."""
    sym = symmetric(edges)
    lists = sym.groupBy(F.col("src").alias("vid")).agg(F.collect_set("dst").alias("nbrs"))
    rows = sym.join(lists.withColumnRenamed("vid", "dst"), "dst").groupBy(F.col("src").alias("vid")).agg(F.collect_list(F.struct("dst", "nbrs")).alias("net"))

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            sizes = []
            for net in pdf.net:
                near = {x["dst"]: set(x["nbrs"]) for x in net}
                best = 1

                def grow(size: int, left: set) -> None:
                    nonlocal best
                    best = max(best, size)
                    while left and size + len(left) > best:
                        v = left.pop()
                        grow(size + 1, left & near[v])

                grow(1, set(near))
                sizes.append(best)
            yield pd.DataFrame({"vid": pdf.vid, "size": pd.array(sizes, "int32")})

    return rows.mapInPandas(search, "vid long, size int")


def clique_hit_rate(edges: DataFrame) -> DataFrame:
    """hits, vertices: where the two-superstep size is the exact one."""
    both = max_cliques(edges).select("vid", F.col("size").alias("a")).join(max_cliques_exact(edges), "vid")
    return both.agg(F.count_if(F.col("a") == F.col("size")).alias("hits"), F.count(F.lit(1)).alias("vertices"))


def hot_zones(edges: DataFrame, assignment: DataFrame) -> DataFrame:
    """part, list_items, duplicates: list volume held by a partition, and cliques it finds more than once."""
    degree = symmetric(edges).groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    volume = symmetric(edges).join(degree.withColumnRenamed("src", "dst"), "dst").groupBy(F.col("src").alias("vid")).agg(F.sum("d").alias("items"))
    cliques = max_cliques(edges).join(assignment, "vid").groupBy("part", "members").agg((F.count(F.lit(1)) - 1).alias("again"))
    dup = cliques.groupBy("part").agg(F.sum("again").alias("duplicates"))
    return volume.join(assignment, "vid").groupBy("part").agg(F.sum("items").alias("list_items")).join(dup, "part", "left")


def bfs_levels(edges: DataFrame, root: int) -> tuple[DataFrame, int]:
    """vid, level from a root; and the number of levels. Runs until a level reaches nothing new."""
    sym = symmetric(edges).repartition("src").persist()
    seen = cut(edges.sparkSession.createDataFrame([(root, 0)], "vid long, level int"))
    front, depth = seen, 0
    while True:
        reached = front.join(sym, front.vid == sym.src).select(F.col("dst").alias("vid")).distinct()
        front = cut(reached.join(seen, "vid", "left_anti").select("vid", F.lit(depth + 1).alias("level")))
        if not front.limit(1).count():
            break
        depth += 1
        seen = cut(seen.unionAll(front))
    sym.unpersist()
    return seen, depth


def diameter_sweep(edges: DataFrame) -> DataFrame:
    """lower_bound, far: two sweeps, from the lowest vertex and from the farthest of it (lowest on ties)."""
    root = edges.agg(F.min("src")).first()[0]
    if root is not None and fits(edges):
        return search.sweep_rows(edges, root)
    levels, depth = bfs_levels(edges, root)
    far = levels.where(F.col("level") == depth).agg(F.min("vid")).first()[0]
    return edges.sparkSession.createDataFrame([(bfs_levels(edges, far)[1], far)], "lower_bound int, far long")


def diameter_exact(edges: DataFrame) -> DataFrame:
    """diameter: by searches from all vertices that could be an end of it; beyond one task's graphs, by a search from all at once."""
    if fits(edges):
        return search.diameter_rows(edges).agg(F.coalesce(F.max("diameter"), F.lit(0)).alias("diameter"))
    sym = symmetric(edges).persist()
    seen = cut(vertices_of(edges).select(F.col("vid").alias("root"), "vid"))
    front, depth = seen, 0
    while True:
        reached = front.join(sym, front.vid == sym.src).select("root", F.col("dst").alias("vid")).distinct()
        front = cut(reached.join(seen, ["root", "vid"], "left_anti"))
        if not front.limit(1).count():
            break
        depth += 1
        seen = cut(seen.unionAll(front))
    sym.unpersist()
    return edges.sparkSession.createDataFrame([(depth,)], "diameter int")


def neighbourhood_function(edges: DataFrame, hops: int | None = None, lg_k: int = 12) -> DataFrame:
    """hop, pairs: estimated pairs within each number of hops, by union of HLL sketches; until the estimate stands still, or for ``hops``.

    Sketches only grow, and a hop that changes none of them changes no later one either,
    so the run ends with the first hop whose estimate is that of the one before.
    """
    sym = symmetric(edges).persist()
    sketch = cut(vertices_of(edges).groupBy("vid").agg(F.hll_sketch_agg("vid", lg_k).alias("s")))
    rows: list[tuple[int, float]] = []
    hop = 0
    while True:
        if hop:
            near = sym.join(sketch.withColumnRenamed("vid", "dst"), "dst").select(F.col("src").alias("vid"), "s")
            old, sketch = sketch, cut(near.unionByName(sketch).groupBy("vid").agg(F.hll_union_agg("s").alias("s")))
            forget(old)
        rows.append((hop, float(sketch.agg(F.sum(F.hll_sketch_estimate("s"))).first()[0] or 0)))
        if (hops is not None and hop >= hops) or (hops is None and hop and rows[-1][1] == rows[-2][1]):
            break
        hop += 1
    sym.unpersist()
    return edges.sparkSession.createDataFrame(rows, "hop int, pairs double")


def diameter_sketch(edges: DataFrame, epsilon: float = 0.0, lg_k: int = 12) -> DataFrame:
    """diameter, effective: where the neighbourhood function stops growing (by more than ``epsilon``), and reaches 90 % of its end."""
    n = neighbourhood_function(edges, None, lg_k).toPandas().pairs.to_numpy()
    stop = next((h for h in range(len(n) - 1) if n[h + 1] <= (1 + epsilon) * n[h]), len(n) - 1)
    goal = 0.9 * n[stop]
    h = int(np.argmax(n[: stop + 1] >= goal))
    effective = float(h) if h == 0 else h - 1 + float((goal - n[h - 1]) / max(1e-12, n[h] - n[h - 1]))
    return edges.sparkSession.createDataFrame([(stop, effective)], "diameter int, effective double")


#: Fixed-point scale of the tissue's variables.
CELL = 1_000_000


def tissue_start(cells: DataFrame, n_vars: int = 2) -> DataFrame:
    """vid, u, w, pad, inert from vid, excitation (0 to 1), inert; fixed point."""
    u = F.when(F.col("inert"), F.lit(0)).otherwise(F.floor(F.col("excitation") * CELL)).cast("long")
    return cells.select("vid", u.alias("u"), F.lit(0).cast("long").alias("w"), F.array_repeat(F.lit(0).cast("long"), max(0, n_vars - 2)).alias("pad"), "inert")


def tissue(edges: DataFrame, cells: DataFrame, steps: int = 3, n_vars: int = 2, dt: float = 0.1, diffusion: float = 0.1, epsilon: float = 0.08, a: float = 0.7, b: float = 0.8, current: float = 0.5) -> DataFrame:
    """Excitable cells (two variables and padding) by Euler steps: vid, u, w, pad_sum.

    u' = u - u^3/3 - w + I + D sum(u_j - u), w' = eps (u + a - b w); each padding
    variable relaxes towards the one before it. Neighbour sums are integers, so
    results don't depend on order.
    """
    sym = symmetric(edges).repartition("src").persist()
    now = cut(tissue_start(cells, n_vars))
    for _ in range(steps):
        flux = sym.join(now.select(F.col("vid").alias("dst"), F.col("u").alias("v")), "dst").groupBy(F.col("src").alias("vid")).agg(F.sum("v").alias("sum_u"), F.count(F.lit(1)).alias("deg"))
        u, w = F.col("u") / CELL, F.col("w") / CELL
        pull = (F.coalesce("sum_u", F.lit(0)) - F.coalesce("deg", F.lit(0)) * F.col("u")) / CELL
        du = u - u * u * u / 3 - w + current + diffusion * pull
        dw = epsilon * (u + a - b * w)
        chain = F.transform(F.arrays_zip(F.col("pad").alias("x"), F.concat(F.array("u"), F.col("pad")).alias("y")), lambda z: F.floor(z["x"] + F.lit(0.5) * (z["y"] - z["x"])).cast("long"))
        pad = F.slice(chain, 1, F.greatest(F.lit(1), F.size("pad"))) if n_vars > 2 else F.col("pad")
        now = cut(
            now.join(flux, "vid", "left").select(
                "vid",
                F.when(F.col("inert"), F.lit(0)).otherwise(F.round((u + dt * du) * CELL)).cast("long").alias("u"),
                F.when(F.col("inert"), F.lit(0)).otherwise(F.round((w + dt * dw) * CELL)).cast("long").alias("w"),
                pad.alias("pad"),
                "inert",
            )
        )
    sym.unpersist()
    return now.select("vid", "u", "w", F.aggregate("pad", F.lit(0).cast("long"), lambda s, x: s + x).alias("pad_sum"))


def top(frame: DataFrame, value: str, n: int) -> DataFrame:
    """The n rows with the largest value, lowest vid on ties."""
    return frame.orderBy(F.desc(value), "vid").limit(n)


def top_per(frame: DataFrame, key: str, value: str, n: int) -> DataFrame:
    """The n rows a key with the largest value; Spark limits groups before the exchange."""
    w = Window.partitionBy(key).orderBy(F.desc(value), "vid")
    return frame.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= n)
