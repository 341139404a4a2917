"""Many adaptations side by side: sweeps over settings, seeds and starts.

Where a graph fits in one task (a checked number of edges), a run of hundreds of short
iterations is one pass of array code instead of hundreds of jobs. A sweep's runs are
dealt over as many tasks as there are cores, each of which reads the graph once. The rules and the hashes are those of ``migrate``, bit for bit; beyond the
bound each run is the distributed loop.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphdrift.config import MigrationConfig
from graphdrift.functions.hashing import ADMIT, COIN, FACTOR, MASK, PLACE, TIE, threshold
from graphdrift.functions.lineage import cut, setting
from graphdrift.operators.graph import vertices_of

#: Edges up to which a run is one task's work. Its arrays take 16 bytes an edge while arcs are
#: sorted (12 where ids differ by less than 2**32, so the bound is a third higher) and 8
#: afterwards, and about k + 30 a vertex: 0.7 GB resident for a cube of 9 million cells.
ONE_TASK_EDGES = 60_000_000
#: Edges up to which a stream of vertices is one task's work (it keeps a dictionary of places).
STREAM_EDGES = 4_000_000
#: Cells or arcs that are handled at once.
BLOCK = 1 << 21
#: Pairs of numbers in a packed row: an Arrow batch of 10,000 rows holds 80 MB.
PAIRS = 512
#: Kinds of packed rows; others are numbers of starts.
EDGE, VERTEX = -2, -1

COLUMNS = ["iteration", "proposed", "damped", "refused", "moved", "cut", "edges", "max_load", "min_load", "messages", "remote", "grouped", "step_ms"]


def hashed(vid: np.ndarray, seed: int, use: int, t: int = 0, part: np.ndarray | int = 0) -> np.ndarray:
    """The engine's 32-bit hash."""
    mask = np.uint64(MASK)
    salt = np.uint64(seed * 7919 + use * 15485863 + t * 104729) + np.asarray(part).astype(np.uint64) * np.uint64(1299709)
    v = vid.astype(np.uint64)
    v = (((v ^ (v >> np.uint64(32))) & mask) + salt) & mask
    for _ in range(2):
        v = ((v >> np.uint64(16) ^ v) * np.uint64(FACTOR)) & mask
    return (v >> np.uint64(16) ^ v).astype(np.int64)


def places(vid: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    """What finds the places of ids among the (sorted) ids."""
    if not len(vid):
        return lambda x: np.searchsorted(vid, x).astype(np.uint64)
    low, span = int(vid[0]), int(vid[-1]) - int(vid[0]) + 1
    if span == len(vid):  # no gaps
        return lambda x: (x - low).astype(np.uint64)
    if span < 4 * len(vid):
        table = np.zeros(span, np.uint32)
        table[vid - low] = np.arange(len(vid), dtype=np.uint32)
        return lambda x: table[x - low].astype(np.uint64)
    return lambda x: np.searchsorted(vid, x).astype(np.uint64)


def ids_of(ends: np.ndarray) -> np.ndarray:
    """The distinct ids among the ends of edges (unsigned numbers; short ones are offsets), ascending."""
    ends = ends.view(np.int64) if ends.itemsize == 8 else ends
    if not len(ends):
        return ends.astype(np.int64)
    low, high = int(ends.min()), int(ends.max())
    if high - low < 4 * len(ends):
        seen = np.zeros(high - low + 1, bool)
        for x in range(0, len(ends), BLOCK):
            seen[ends[x : x + BLOCK] - low] = True
        return np.flatnonzero(seen) + low
    return np.unique(np.concatenate([np.unique(ends[x : x + BLOCK]) for x in range(0, len(ends), BLOCK)])).astype(np.int64)


def arc_keys(vid: np.ndarray, arcs: np.ndarray) -> np.ndarray:
    """All sources, then all targets of edges become both arcs of every edge, in place: the place of an arc's source, then its target's."""
    place, size = places(vid), len(arcs) // 2
    for x in range(0, size, BLOCK):
        y = min(size, x + BLOCK)
        a, b = place(arcs[x:y].view(np.int64)), place(arcs[size + x : size + y].view(np.int64))
        arcs[x:y], arcs[size + x : size + y] = a << np.uint64(32) | b, b << np.uint64(32) | a
    return arcs


class Graph:
    """Neighbours in one array by vertex. Runs on one graph share it."""

    def __init__(self, vid: np.ndarray, arcs: np.ndarray):
        """``arcs`` (sources, then targets, as unsigned numbers) are used up."""
        self.vid, self.edges = vid, len(arcs) // 2
        arcs = arc_keys(vid, arcs)
        arcs.sort()
        self.first = np.searchsorted(arcs, np.arange(len(vid) + 1, dtype=np.uint64) << np.uint64(32))
        # the targets move to the front of the keys' own memory, the rest of which is given back
        words = arcs.view(np.uint32)
        for x in range(0, len(arcs), BLOCK):
            words[x : x + BLOCK][: len(arcs) - x] = words[2 * x : 2 * (x + BLOCK) : 2].copy()
        del words
        arcs.resize(self.edges, refcheck=False)
        self.near_to = arcs.view(np.int32)

    @classmethod
    def of_pairs(cls, pairs: np.ndarray, low: int, vid: np.ndarray | None = None) -> Graph:
        """The same from edges that are one number each (offsets from ``low`` of the source, then of the target, 32 bits
        each), which are used up. Arcs in the edges' direction are sorted first, the others then in the same memory."""
        self = cls.__new__(cls)
        words, size = pairs.view(np.uint32), len(pairs)
        vid = ids_of(words) + low if vid is None else vid
        self.vid, self.edges = vid, size
        place, starts = places(vid), np.arange(len(vid) + 1, dtype=np.uint64) << np.uint64(32)
        for x in range(0, len(words), BLOCK):
            words[x : x + BLOCK] = place(words[x : x + BLOCK].astype(np.int64) + low)
        pairs.sort()
        there, after = np.searchsorted(pairs, starts), np.empty(size, np.uint32)
        for x in range(0, size, BLOCK):
            some = pairs[x : x + BLOCK]
            after[x : x + BLOCK] = words[2 * x : 2 * (x + BLOCK) : 2]
            some[:] = some << np.uint64(32) | some >> np.uint64(32)
        pairs.sort()
        back = np.searchsorted(pairs, starts)
        del starts
        for x in range(0, size, BLOCK):
            words[x : x + BLOCK][: size - x] = words[2 * x : 2 * (x + BLOCK) : 2].copy()
        del words
        pairs.resize(-(-size // 2), refcheck=False)
        before = pairs.view(np.uint32)[:size]
        self.first, self.near_to = there + back, np.empty(2 * size, np.int32)
        # from the end on, so that both halves shrink as their memory is needed
        b = len(vid)
        while b > 0:
            a = min(b - 1, int(np.searchsorted(self.first, self.first[b] - 4 * BLOCK)))
            out = self.near_to[self.first[a] : self.first[b]]
            out[np.arange(back[a], back[b]) - back[a] + np.repeat(there[a:b] - there[a], np.diff(back[a : b + 1]))] = before[back[a] : back[b]]
            out[np.arange(there[a], there[b]) - there[a] + np.repeat(back[a + 1 : b + 1] - back[a], np.diff(there[a : b + 1]))] = after[there[a] : there[b]]
            del before
            after.resize(there[a], refcheck=False)
            pairs.resize(-(-int(back[a]) // 2), refcheck=False)
            before, b = pairs.view(np.uint32), a
        return self


def placed(rule: str, vid: np.ndarray, k: int, seed: int) -> np.ndarray:
    """The starts that need nothing but ids (see ``initial``): hsh, hsh_mixed, rnd."""
    if rule == "hsh":
        return (vid % k).astype(np.int16)
    h = np.concatenate([hashed(vid[x : x + BLOCK], seed, PLACE) for x in range(0, len(vid), BLOCK)] or [np.zeros(0, np.int64)])
    if rule == "hsh_mixed":
        return (h % k).astype(np.int16)
    part = np.empty(len(vid), np.int16)
    part[np.argsort(h, kind="stable")] = np.arange(len(vid)) % k
    return part


class Replica:
    """One adaptation over arrays.

    What each vertex has in each partition is kept up to date from the movers'
    neighbours alone, so an iteration costs what moves.
    """

    def __init__(self, src: np.ndarray, dst: np.ndarray, vid: np.ndarray, part: np.ndarray, cfg: MigrationConfig, caps: list[int] | None = None, graph: Graph | None = None):
        """``graph`` is that of ``vid`` instead of ``src`` and ``dst``."""
        self.cfg, self.vid = cfg, vid
        n, k = len(vid), cfg.k
        graph = graph or Graph(vid, np.concatenate([src, dst]).astype(np.uint64))
        self.edges, self.first, self.near_to = graph.edges, graph.first, graph.near_to
        self.part = part.astype(np.int16)
        self.home = self.part.copy() if cfg.deferred else self.part
        self.settle = np.full(n, -1, np.int32) if cfg.deferred else None
        self.t = 0
        self.loads = np.bincount(self.part, minlength=k)
        from graphdrift.operators.migrate import capacity_plan

        self.caps = caps or capacity_plan(n, k, cfg.slack if cfg.use_quota else None, cfg.caps, self.loads.tolist())
        self.near = self.counts()
        self.willing, self.own, self.others = np.zeros(n, bool), np.zeros(n, np.int32), np.zeros(n, np.int16)
        self.told = self.kept = 0  # the sums of others and own
        self._judge(np.arange(n, dtype=np.int32))
        self.rows: list[tuple] = []

    def counts(self) -> np.ndarray:
        """Neighbours of every vertex in every partition (itself among them with count_self), in the narrowest numbers that hold them."""
        n, k = len(self.vid), self.cfg.k
        most = int(np.diff(self.first).max(initial=0)) + 1
        near = np.zeros((n, k), next(t for t in (np.uint8, np.uint16, np.uint32) if most <= np.iinfo(t).max))
        for a, b in self._pieces():
            size = np.diff(self.first[a : b + 1])
            cells = np.repeat(np.arange(b - a), size) * k + self.part[self.near_to[self.first[a] : self.first[b]]]
            near[a:b] = np.bincount(cells, minlength=(b - a) * k).reshape(-1, k)
        if self.cfg.count_self:
            near[np.arange(n), self.part] += 1
        return near

    def _pieces(self):
        """Ranges of vertices with about BLOCK cells or arcs each."""
        n, a = len(self.vid), 0
        while a < n:
            b = min(n, a + max(1, BLOCK // self.cfg.k), max(a + 1, int(np.searchsorted(self.first, self.first[a] + BLOCK))))
            yield a, b
            a = b

    def _judge(self, ids: np.ndarray) -> None:
        """Who of these would rather be elsewhere; their neighbours at home, and the other partitions they have neighbours in."""
        step = max(1, BLOCK // self.cfg.k)
        for x in range(0, len(ids), step):
            v = ids[x : x + step]
            near, here = self.near[v], self.part[v]
            own = near[np.arange(len(v)), here]
            across = np.ascontiguousarray(near.T)  # a short row is slow to reduce
            self.willing[v] = own < np.maximum.reduce(across) if self.cfg.candidate_rule == "majority" else (own == 0) & across.any(axis=0)
            others = np.count_nonzero(across, axis=0) - (own > 0)
            own = own.astype(np.int32) - int(self.cfg.count_self)
            self.told += int(others.sum()) - int(self.others[v].sum(dtype=np.int64))
            self.kept += int(own.sum(dtype=np.int64)) - int(self.own[v].sum(dtype=np.int64))
            self.others[v], self.own[v] = others, own
        self.cut = (2 * self.edges - self.kept) // 2

    def _wanted(self, v: np.ndarray) -> np.ndarray:
        """The partition that each of these willing ones asks for: most neighbours, ties by hash, then the lowest."""
        cfg, step, out = self.cfg, max(1, BLOCK // self.cfg.k), np.empty(len(v), np.int16)
        for x in range(0, len(v), step):
            near = self.near[v[x : x + step]]
            best = near == near.max(axis=1)[:, None] if cfg.candidate_rule == "majority" else near > 0
            if cfg.tie_break == "hash":
                row, p = np.nonzero(best)
                tie = np.full(best.shape, -1, np.int64)
                tie[row, p] = hashed(self.vid[v[x : x + step]][row], cfg.seed, TIE, self.t, p)
                out[x : x + step] = tie.argmax(axis=1)
            else:
                out[x : x + step] = best.argmax(axis=1)
        return out

    def _move(self, v: np.ndarray, want: np.ndarray) -> None:
        """All of these change place at once; they and their neighbours are judged anew."""
        k, flat = self.cfg.k, self.near.reshape(-1)
        old = self.part[v]
        size = self.first[v + 1] - self.first[v]
        total, x = np.cumsum(size), 0
        # a few neighbours are listed, many are marked
        few = 16 * (total[-1] + len(v)) < len(self.vid)
        touched = [v] if few else np.zeros(len(self.vid), bool)
        one = flat.dtype.type(1)
        while x < len(v):
            y = max(x + 1, int(np.searchsorted(total, (total[x - 1] if x else 0) + BLOCK)))
            s = size[x:y]
            at = np.repeat(self.first[v[x:y]] - (np.cumsum(s) - s), s) + np.arange(s.sum())
            to = self.near_to[at].astype(np.int64)
            if few:
                touched.append(to.copy())
            else:
                touched[to] = True
            to *= k
            np.subtract.at(flat, to + np.repeat(old[x:y], s), one)
            np.add.at(flat, to + np.repeat(want[x:y], s), one)
            x = y
        if self.cfg.count_self:
            self.near[v, old] -= one
            self.near[v, want] += one
        self.part[v] = want
        self.loads = self.loads + np.bincount(want, minlength=k) - np.bincount(old, minlength=k)
        if not few:
            touched[v] = True
            touched = np.flatnonzero(touched)
        else:
            touched = np.sort(np.concatenate(touched))
            touched = touched[np.concatenate([[True], touched[1:] != touched[:-1]])]
        self._judge(touched)

    def _hashes(self, v: np.ndarray, use: int) -> np.ndarray:
        return np.concatenate([hashed(self.vid[v[x : x + BLOCK]], self.cfg.seed, use, self.t) for x in range(0, len(v), BLOCK)] or [np.zeros(0, np.int64)])

    def step(self) -> int:
        cfg, k, began = self.cfg, self.cfg.k, time.perf_counter()
        self.t = t = self.t + 1
        seen, told, remote = self.edges, self.told, 2 * self.cut
        wanted = np.flatnonzero(self.willing)
        if cfg.deferred:
            wanted = wanted[self.settle[wanted] < t]
        n = len(wanted)
        who = wanted[self._hashes(wanted, COIN) < threshold(cfg.s if cfg.adaptive else 0.0)]
        want, acted = self._wanted(who), len(who)
        if cfg.use_quota and acted:
            here = self.part[who].astype(np.int64)
            pair = here * k + want
            gain = self.near[who, want].astype(np.int64) - self.near[who, here]
            first = gain.max() - gain if cfg.admission == "gain" else np.zeros(acted, np.int64)
            # pair, gain and hash in one number where they fit; ids ascend already
            if (int(pair.max()) + 1) * (int(first.max()) + 1) < 1 << 31:
                order = np.argsort((pair * (int(first.max()) + 1) + first) << 32 | self._hashes(who, ADMIT), kind="stable")
            else:
                order = np.lexsort((self._hashes(who, ADMIT), first, pair))
            sorted_pair = pair[order]
            begin = np.flatnonzero(np.concatenate([[True], sorted_pair[1:] != sorted_pair[:-1]]))
            place = np.arange(acted) - np.repeat(begin, np.diff(np.append(begin, acted)))
            i, j = sorted_pair // k, sorted_pair % k
            room = np.maximum(0, np.array(self.caps) - self.loads)[j]
            quota = room // (k - 1)
            if cfg.quota_remainder == "rotate":
                quota = quota + ((np.where(i < j, i, i - 1) - t) % (k - 1) < room % (k - 1))
            let = np.sort(order[place < quota])
            who, want = who[let], want[let]
        m = len(who)
        if cfg.deferred:
            moved = np.zeros(len(self.vid), bool)
            moved[who] = True
            self.home = np.where((self.settle >= 0) & (self.settle <= t) & ~moved, self.part, self.home)
            self.settle = np.where(moved, t + 1, np.where(self.settle > t, self.settle, -1))
        if m:
            self._move(who, want)
        self.rows.append((t, n, n - acted, acted - m, m, self.cut, seen, int(self.loads.max()), int(self.loads.min()), 2 * seen, remote, told, round(1000 * (time.perf_counter() - began))))
        return m

    def run(self, iterations: int | None) -> bool:
        """To quiescence or for so many iterations; has it become quiet?"""
        still = 0
        while self.t < (self.cfg.max_iter if iterations is None else iterations):
            still = 0 if self.step() else still + 1
            if iterations is None and still > self.cfg.patience:
                break
        return still > self.cfg.patience


@dataclass(frozen=True)
class Held:
    """Edges in the shared folder, packed: tasks read them there, each all of them, without a shuffle."""

    rows: DataFrame
    size: int
    low: int
    high: int

    @property
    def narrow(self) -> bool:
        """Do ids fit in 32 bits from the lowest one?"""
        return self.high - self.low < 1 << 32

    @property
    def fits(self) -> bool:
        """Is a run on them one task's work?"""
        return self.size <= (ONE_TASK_EDGES * 4 // 3 if self.narrow else ONE_TASK_EDGES)

    def frame(self) -> DataFrame:
        """src, dst."""

        def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for x in range(0, len(batch), 100):
                    for _, pairs in unpacked(batch.slice(x, 100)):
                        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, c]) for c in range(2)], names=["src", "dst"])

        return self.rows.mapInArrow(unpack, "src long, dst long")


def hold(edges: DataFrame | Held, tasks: tuple[int, ...] = (0,)) -> Held:
    """Edges (src, dst) written once, packed; what is held already stays."""
    if isinstance(edges, Held):
        return edges
    rows = cut(packed(edges.select(F.col("src").cast("long"), F.col("dst").cast("long")), list(tasks), EDGE))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ends = np.array([np.frombuffer(x, np.int64, 3) for x in batch.column(2).to_pylist()]).reshape(-1, 3)
            yield pa.RecordBatch.from_arrays([pa.array(ends[:, c]) for c in range(3)], names=["size", "low", "high"])

    whole = rows.mapInArrow(measure, "size long, low long, high long").agg(F.sum("size"), F.min("low"), F.max("high")).first()
    return Held(rows, *(x or 0 for x in whole))


def fits(edges: DataFrame | Held) -> bool:
    return edges.fits if isinstance(edges, Held) else edges.count() <= ONE_TASK_EDGES


def frame_of(edges: DataFrame | Held) -> DataFrame:
    """src, dst."""
    return edges.frame() if isinstance(edges, Held) else edges


def streams(edges: DataFrame) -> bool:
    return edges.count() <= STREAM_EDGES


def packed(pairs: DataFrame, tasks: list[int], kind: int) -> DataFrame:
    """tasks, kind, data: two columns of long as rows of PAIRS pairs, each for every one of ``tasks``.

    A row begins with the number of pairs, the lowest and the highest of its numbers;
    those are offsets from the lowest, of 32 bits where they fit.
    """

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            flat, data = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in range(2)], axis=1).astype(np.int64), []
            for x in range(0, len(flat), PAIRS):
                some = flat[x : x + PAIRS]
                low, high = int(some.min()), int(some.max())
                body = (some - low).astype(np.uint32) if high - low < 1 << 32 else some
                data.append(np.array([len(some), low, high]).tobytes() + body.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(data, pa.binary())], names=["data"])

    return pairs.mapInArrow(pack, "data binary").select(F.array(*[F.lit(t) for t in tasks]).alias("tasks"), F.lit(kind).alias("kind"), "data")


def sent(rows: DataFrame, tasks: int) -> DataFrame:
    """task, kind, data: packed rows dealt to their tasks."""
    return rows.select(F.explode("tasks").alias("task"), "kind", "data").repartitionById(tasks, F.col("task"))


def row_pairs(row: bytes) -> np.ndarray:
    """The pairs of one packed row."""
    _, low, high = np.frombuffer(row, np.int64, 3).tolist()
    if high - low < 1 << 32:
        return np.frombuffer(row, np.uint32, offset=24).astype(np.int64).reshape(-1, 2) + low
    return np.frombuffer(row, np.int64, offset=24).reshape(-1, 2)


def unpacked(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray]]:
    """kind and pairs of stretches of ``packed`` rows."""
    kind, data = batch.column(1).to_numpy(zero_copy_only=False), batch.column(2)
    cuts = np.flatnonzero(np.diff(kind)) + 1
    for x, y in zip([0, *cuts], [*cuts, len(kind)]):
        if x < y:
            yield int(kind[x]), np.concatenate([row_pairs(r) for r in data.slice(x, y - x).to_pylist()])


def adapt_many(edges: DataFrame | Held, starts: DataFrame | dict[int, DataFrame | str], runs: dict[int, MigrationConfig], iterations: int | None = None) -> tuple[DataFrame | None, DataFrame]:
    """Final states (run, vid, part, home, settle) and histories (run, COLUMNS, quiet) of all runs.

    ``starts``: run, vid, part of every run; or a placement (vid, part) or rule (see
    ``placed``) by run, for histories alone. All runs have the same vertices; where all
    begin by rules, these are the ends of the edges that a task has anyway. A task reads
    the edges once, packed, and does its share of the runs one after another; the caller
    has checked the number of edges (``fits``). A history's messages, remote and grouped
    ones are those of a superstep in which every vertex tells every neighbour, before the
    iteration's moves; step_ms is the time of the array code alone.
    """
    spark, states = (edges.rows if isinstance(edges, Held) else edges).sparkSession, not isinstance(starts, dict)
    tasks = min(len(runs), spark.sparkContext.defaultParallelism)
    whole_graph = hold(edges, tuple(range(tasks)))
    size, low, narrow = whole_graph.size, whole_graph.low, whole_graph.narrow
    task_of = {r: i % tasks for i, r in enumerate(runs)}
    begun: dict[int, int | str] = {}  # a run's rule, or the kind of the rows that hold its start
    rows = {t: [whole_graph.rows] for t in range(tasks)}  # what a task reads
    if states:
        held = {r: starts.where(F.col("run") == r) for r in runs}
    else:
        held = starts
        if 0 < sum(isinstance(a, str) for a in held.values()) < len(held):
            vertices = cut(packed(vertices_of(whole_graph.frame()).select(F.col("vid").cast("long"), F.lit(0).cast("long")), list(rows), VERTEX))
            for t in rows:
                rows[t].append(vertices)
    frames: dict[int, int] = {}
    for r, a in held.items():
        begun[r] = a if isinstance(a, str) else frames.setdefault(id(a), len(frames))
    for a, kind in {id(a): (a, frames[id(a)]) for a in held.values() if not isinstance(a, str)}.values():
        readers = sorted({task_of[r] for r in runs if begun[r] == kind})
        start = cut(packed(a.select(F.col("vid").cast("long"), F.col("part").cast("long")), readers, kind))
        for t in readers:
            rows[t].append(start)

    def listed(run: int, kind: int, columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        for x in range(0, len(columns[0]), 50_000):
            flat = np.stack([c[x : x + 50_000] for c in columns], axis=1).astype(np.int64)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, flat.size + 1, flat.shape[1], dtype=np.int32)), pa.array(flat.ravel()))
            same = lambda v: pa.array(np.full(len(flat), v, np.int32))
            yield pa.RecordBatch.from_arrays([same(run), lists, same(kind)], names=["run", "x", "kind"])

    def finished(run: int, graph: Graph, part: np.ndarray) -> Iterator[pa.RecordBatch]:
        none = np.zeros(0, np.int64)
        one = Replica(none, none, graph.vid, part, runs[run], graph=graph)
        quiet = one.run(iterations)
        if states:
            settle = np.full(len(one.vid), -1) if one.settle is None else one.settle
            yield from listed(run, 0, [one.vid, one.part, one.home, settle])
        if one.rows:
            yield from listed(run, 1, [*np.array(one.rows, np.int64).T, np.full(len(one.rows), int(quiet))])

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A task's rows come in any order."""
        task, arcs, filled, found = None, np.empty(0, np.uint64), 0, {}
        for batch in batches:
            if task is None and len(batch):
                task, arcs = batch.column(0)[0].as_py(), np.empty(size if narrow else 2 * size, np.uint64)
            for kind, pairs in unpacked(batch):
                if kind == EDGE and narrow:
                    ends = (pairs - low).view(np.uint64)
                    arcs[filled : filled + len(ends)] = ends[:, 0] << np.uint64(32) | ends[:, 1]
                    filled += len(ends)
                elif kind == EDGE:
                    arcs[filled : filled + len(pairs)], arcs[size + filled : size + filled + len(pairs)] = pairs[:, 0], pairs[:, 1]
                    filled += len(pairs)
                else:
                    found.setdefault(kind, []).append((pairs[:, 0].copy(), pairs[:, 1].astype(np.int16)))
        vid, parts = None, {}
        for kind in sorted(found):
            ids, part = (np.concatenate(c) for c in zip(*found.pop(kind)))
            order = np.argsort(ids, kind="stable")
            vid, parts[kind] = ids[order] if vid is None else vid, part[order]
            if len(ids) != len(vid) or (ids[order] != vid).any():
                raise ValueError("runs side by side have the same vertices")
        if task is None:
            return
        graph = Graph.of_pairs(arcs, low, vid) if narrow else Graph(ids_of(arcs) if vid is None else vid, arcs)
        del arcs
        for run, at in task_of.items():
            if at == task:
                how = begun[run]
                yield from finished(run, graph, placed(how, graph.vid, runs[run].k, runs[run].seed) if isinstance(how, str) else parts[how])

    read = [reduce(DataFrame.unionAll, found).coalesce(1).select(F.lit(t).alias("task"), "kind", "data") for t, found in rows.items()]
    # the union would put the single partitions of all tasks together
    with setting(spark, "spark.sql.unionOutputPartitioning", "false"):
        out = cut(reduce(DataFrame.unionAll, read).mapInArrow(whole, "run int, x array<long>, kind int"))
    x = F.col("x")
    state = out.where("kind = 0").select("run", x[0].alias("vid"), x[1].cast("int").alias("part"), x[2].cast("int").alias("home"), F.when(x[3] >= 0, x[3].cast("int")).alias("settle"))
    cells = [x[i].cast("int" if c == "iteration" else "long").alias(c) for i, c in enumerate(COLUMNS)]
    return state if states else None, out.where("kind = 1").select("run", *cells, (x[len(COLUMNS)] == 1).alias("quiet"))


def adapt_growing(ties: DataFrame, slices: int, cfg: MigrationConfig, iterations: int | None = None, onward: bool = False) -> DataFrame:
    """slice, cut, edges, quiet: what a run leaves on the ties (src, dst, slice) up to each slice that has any.

    It begins with the mixed hash; ``onward``: with what the slice before left, and
    newcomers by hash. Then one task does all slices in turn, else they are dealt over
    tasks. The caller has checked the number of ties (``fits``).
    """
    tasks = 1 if onward else max(1, min(slices, ties.sparkSession.sparkContext.defaultParallelism))
    rows = [packed(ties.where(F.col("slice") == d).select(F.col("src").cast("long"), F.col("dst").cast("long")), sorted({x % tasks for x in range(d, slices)}), d) for d in range(slices)]

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, found = None, {}
        for batch in batches:
            if task is None and len(batch):
                task = batch.column(0)[0].as_py()
            for kind, pairs in unpacked(batch):
                found.setdefault(kind, []).append(pairs)
        if task is None:
            return
        new = [len(np.concatenate(found[d])) if d in found else 0 for d in range(slices)]
        pairs = np.concatenate([p for d in sorted(found) for p in found[d]])
        found.clear()
        vid, part, out = np.zeros(0, np.int64), np.zeros(0, np.int16), []
        for d in range(task, slices, tasks):
            size = sum(new[: d + 1])
            if not size:
                continue
            arcs = pairs[:size].T.ravel().astype(np.uint64)
            graph = Graph(np.unique(arcs.view(np.int64)), arcs)
            del arcs
            begun = placed("hsh_mixed", graph.vid, cfg.k, cfg.seed)
            if onward:
                begun[np.searchsorted(graph.vid, vid)] = part
            none = np.zeros(0, np.int64)
            one = Replica(none, none, graph.vid, begun, cfg, graph=graph)
            quiet = one.run(iterations)
            vid, part = one.vid, one.part
            out.append((d, one.cut, size, quiet))
        yield pa.RecordBatch.from_pylist([dict(zip(["slice", "cut", "edges", "quiet"], r)) for r in out], pa.schema([("slice", pa.int32()), ("cut", pa.int64()), ("edges", pa.int64()), ("quiet", pa.bool_())]))

    return sent(reduce(DataFrame.unionAll, rows), tasks).mapInArrow(ends, "slice int, cut long, edges long, quiet boolean")
