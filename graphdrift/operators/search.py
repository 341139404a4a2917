"""Searches over arrays, where a graph fits in one task (see ``replicas``).

Searches from many vertices run side by side, a bit each: one pass over the arcs takes
64 of them a step further for each word of a vertex. A task takes the edges once.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.functions.hashing import BURN, PICK, threshold
from graphdrift.operators.replicas import BLOCK, EDGE, Graph, hashed, packed, sent, unpacked

#: Searches in a word.
BITS = 64
#: Words that the bits of all vertices may take at once.
WORDS = 1 << 21


def on_graph(edges: DataFrame, tasks: int, work: Callable[[Graph, int], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """Rows of ``work(graph, task)`` of so many tasks; none for a graph without edges."""
    size = edges.count()

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, arcs, filled = None, np.empty(0, np.uint64), 0
        for batch in batches:
            if task is None and len(batch):
                task, arcs = batch.column(0)[0].as_py(), np.empty(2 * size, np.uint64)
            for _, pairs in unpacked(batch):
                arcs[filled : filled + len(pairs)], arcs[size + filled : size + filled + len(pairs)] = pairs[:, 0], pairs[:, 1]
                filled += len(pairs)
        if task is not None:
            graph = Graph(np.unique(arcs.view(np.int64)), arcs)
            del arcs
            yield from work(graph, task)

    rows = packed(edges.select(F.col("src").cast("long"), F.col("dst").cast("long")), list(range(tasks)), EDGE)
    return sent(rows, tasks).mapInArrow(whole, schema)


def spread(graph: Graph, front: np.ndarray) -> np.ndarray:
    """The bits (a row of words a vertex) that each vertex's neighbours have."""
    n, words = front.shape
    out = np.empty_like(front)
    step, a = max(1, BLOCK // words), 0
    while a < n:  # every vertex has a neighbour
        b = min(n, max(a + 1, int(np.searchsorted(graph.first, graph.first[a] + step))))
        x, y = graph.first[a], graph.first[b]
        near = graph.near_to[x:y]
        for w in range(words):
            out[a:b, w] = np.bitwise_or.reduceat(front[:, w][near], graph.first[a:b] - x)
        a = b
    return out


def bits_of(roots: np.ndarray, n: int) -> np.ndarray:
    """The i-th bit at the i-th root. A word is one stretch of memory."""
    out, i = np.zeros((n, -(-len(roots) // BITS)), np.uint64, order="F"), np.arange(len(roots))
    np.bitwise_or.at(out, (roots, i // BITS), np.uint64(1) << (i % BITS).astype(np.uint64))
    return out


def held(words: np.ndarray, size: int) -> np.ndarray:
    """Which of the first ``size`` bits are set."""
    return np.unpackbits(np.ascontiguousarray(words).view(np.uint8), bitorder="little")[:size].astype(bool)


def eccentricities(graph: Graph, roots: np.ndarray, at_level: Callable[[int, np.ndarray], None] | None = None) -> np.ndarray:
    """How far the farthest that a root reaches is; ``at_level`` sees what each level reaches first."""
    seen = bits_of(roots, len(graph.vid))
    front, far, level = seen, np.zeros(len(roots), np.int32), 0
    while True:
        front = spread(graph, front) & ~seen
        grew = held(np.bitwise_or.reduce(front, axis=0), len(roots))
        if not grew.any():
            return far
        level += 1
        far[grew] = level
        seen = seen | front
        if at_level:
            at_level(level, front)


def levels(graph: Graph, root: int) -> np.ndarray:
    """Each vertex's distance from the root (a place, not an id); -1: not reached."""
    level, front, t = np.full(len(graph.vid), -1, np.int32), np.array([root]), 0
    level[root] = 0
    while len(front):
        t += 1
        size = graph.first[front + 1] - graph.first[front]
        near = graph.near_to[np.repeat(graph.first[front] - (np.cumsum(size) - size), size) + np.arange(size.sum())]
        front = np.unique(near[level[near] < 0])
        level[front] = t
    return level


def diameter(graph: Graph, task: int = 0, tasks: int = 1) -> int:
    """The largest eccentricity; with ``tasks``, that of a task's share of the roots and of the first ones.

    The first roots are the best connected vertices. How far a vertex's farthest can be
    is bounded by its distance from one of them and how far that one's farthest is, so
    those that can't exceed what is found already need no search of their own.
    """
    n = len(graph.vid)
    first = np.argsort(-np.diff(graph.first), kind="stable")[: max(1, min(BITS, 16 * BLOCK // n))]
    away = np.full((len(first), n), -1, np.int32)
    away[np.arange(len(first)), first] = 0

    def near(level: int, front: np.ndarray) -> None:
        for i in range(len(first)):
            away[i][(front[:, 0] >> np.uint64(i)) & np.uint64(1) == 1] = level

    far = eccentricities(graph, first, near)
    bound = np.full(n, n, np.int64)
    for i in range(len(first)):
        bound = np.where(away[i] >= 0, np.minimum(bound, far[i] + away[i]), bound)
    bound[first] = 0
    del away
    found, size = int(far.max()), BITS * max(1, WORDS // n)
    left = np.flatnonzero(bound > found)
    # the ones that can be farthest come first, and all tasks get some
    left = left[np.argsort(-bound[left], kind="stable")][task::tasks]
    while len(left):
        found = max(found, int(eccentricities(graph, left[:size]).max()))
        left = left[size:]
        left = left[bound[left] > found]
    return found


def diameter_rows(edges: DataFrame) -> DataFrame:
    """diameter, as found by each task."""
    tasks = edges.sparkSession.sparkContext.defaultParallelism

    def work(graph: Graph, task: int) -> Iterator[pa.RecordBatch]:
        yield pa.RecordBatch.from_arrays([pa.array([diameter(graph, task, tasks)], pa.int32())], names=["diameter"])

    return on_graph(edges, tasks, work, "diameter int")


def sweep_rows(edges: DataFrame, root: int) -> DataFrame:
    """lower_bound, far: two sweeps, from the root and from the farthest of it (lowest on ties)."""

    def work(graph: Graph, task: int) -> Iterator[pa.RecordBatch]:
        one = levels(graph, int(np.searchsorted(graph.vid, root)))
        far = int(np.flatnonzero(one == one.max())[0])
        yield pa.RecordBatch.from_arrays([pa.array([int(levels(graph, far).max())], pa.int32()), pa.array([int(graph.vid[far])], pa.int64())], names=["lower_bound", "far"])

    return on_graph(edges, 1, work, "lower_bound int, far long")


def burn(graph: Graph, new: np.ndarray, p: float, depth: int, seed: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(newcomers, vertices) of the fires of these newcomers, by the rules of ``generators.forest_fire``."""
    n = len(graph.vid)
    for x in range(0, len(new), BITS):
        w = new[x : x + BITS]
        burnt = bits_of((hashed(w, seed, PICK) % n).astype(np.int64), n)
        front, tried = burnt, burnt
        for _ in range(depth):
            # a vertex's coin stays what it was
            asked = (spread(graph, front) & ~tried)[:, 0]
            tried = tried | asked[:, None]
            row = np.flatnonzero(asked)
            front = np.zeros_like(burnt)
            for y in range(0, len(row), BLOCK // BITS):
                some = row[y : y + BLOCK // BITS]
                at, i = np.nonzero(np.unpackbits(asked[some].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
                yes = coins(graph.vid[some[at]], w[i], seed) < threshold(p)
                caught = np.zeros((len(some), BITS), np.uint8)
                caught[at[yes], i[yes]] = 1
                front[some, 0] = np.packbits(caught, axis=1, bitorder="little").view(np.uint64)[:, 0]
            burnt = burnt | front
        row = np.flatnonzero(burnt[:, 0])
        for y in range(0, len(row), BLOCK // BITS):
            some = row[y : y + BLOCK // BITS]
            at, i = np.nonzero(np.unpackbits(burnt[some, 0].copy().view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
            yield w[i], graph.vid[some[at]]


def coins(vid: np.ndarray, newcomer: np.ndarray, seed: int) -> np.ndarray:
    """The coin of each vertex and newcomer: the engine's hash, salted by the newcomer."""
    # a part's salt is a multiple of 1299709, a newcomer's of 31, so the newcomer goes into the id before the mixing
    mask = np.int64(0xFFFFFFFF)
    return hashed(((vid ^ (vid >> 32)) & mask) + newcomer.astype(np.int64) * 31 & mask, seed, BURN)


def fire_rows(edges: DataFrame, first: int, newcomers: int, p: float, depth: int, seed: int) -> DataFrame:
    """src, dst of the fires of ``newcomers`` that are numbered from ``first``."""
    tasks = max(1, min(edges.sparkSession.sparkContext.defaultParallelism, -(-newcomers // BITS)))

    def work(graph: Graph, task: int) -> Iterator[pa.RecordBatch]:
        for w, vid in burn(graph, np.arange(first + task, first + newcomers, tasks), p, depth, seed):
            for x in range(0, len(w), 100_000):
                a, b = w[x : x + 100_000], vid[x : x + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["src", "dst"])

    return on_graph(edges, tasks, work, "src long, dst long")
