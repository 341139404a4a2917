"""Queries without SQL against plain Python over the same tables (edges come from DuckDB, not from Spark)."""

import glob
import os
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from test_quiescence import mixed

from graphdrift.config import MigrationConfig
from graphdrift.functions.hashing import BURN, PICK, PLACE, TIE
from graphdrift.operators import replicas
from graphdrift.operators.migrate import label_propagation
from graphdrift.operators.graph import symmetric
from graphdrift.plans import oracles as o
from graphdrift.plans import registry, workloads

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="needs the test tables")
K = 9


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return con


def edges_of(db, name):
    return sorted(db.execute(o.EDGES[name]).fetchall())


def near_of(edges):
    near = defaultdict(set)
    for a, b in edges:
        near[a].add(b)
        near[b].add(a)
    return near


def hashed(v, k=K, seed=0):
    return mixed(v, seed, PLACE) % k


def cut_of(edges, place):
    return sum(place[a] != place[b] for a, b in edges)


def settled(edges, place, cfg, steps=None):
    """Places and rows after adapting (Replica equals the distributed loop, see test_replicas, and brute force, see test_quiescence)."""
    vid = np.array(sorted(place))
    one = replicas.Replica(np.array([a for a, _ in edges]), np.array([b for _, b in edges]), vid, np.array([place[v] for v in vid]), cfg.but(max_iter=workloads.MAX_ITER))
    one.run(steps)
    return dict(zip(vid.tolist(), one.part.tolist())), one.rows


def run(spark, name, *order):
    rows = registry.queries()[name](spark, SF)
    return (rows.orderBy(*order) if order else rows).collect()


def call_slices(db, days=10):
    rows = db.execute(f"select least(src, dst) a, greatest(src, dst) b, min(date_diff('day', date '2024-01-01', ts::date) // {days}) d from ({o.CALL}) where src <> dst group by 1, 2").fetchall()
    return [[(a, b) for a, b, d in rows if d <= x] for x in range(max(r[2] for r in rows) + 1)]


def greedy(v, near, place, k=K):
    """Newcomers by their placed neighbours."""
    load = Counter(place.values())
    cap = -(-len(place) * 11 // (10 * k)) + 1
    count = Counter(place[x] for x in near[v] if x in place)
    return max(count, key=lambda p: (count[p] * (cap - load[p]), mixed(v, 0, TIE, 0, p), p)) if count else hashed(v)


def first_chunk(vids, k=K):
    """A first chunk of a stream: nothing is placed, so all want the first part; what is over goes to the freest."""
    cap = -(-len(vids) // k)
    spots = sorted((i, p) for p in range(1, k) for i in range(1, cap + 1))
    return dict(zip(vids, [0] * cap + [p for _, p in spots]))


@pytest.mark.parametrize("strategy", ["dtg", "adp", "scratch"])
def test_drift(spark, db, strategy):
    place, want, cfg = {}, [], MigrationConfig()
    for n, edges in enumerate(call_slices(db)):
        near = near_of(edges)
        if strategy == "dtg":
            place = first_chunk(sorted(near)) if not n else place | {v: greedy(v, near, place) for v in near if v not in place}
        elif strategy == "adp":
            place = settled(edges, {v: place.get(v, hashed(v)) for v in near}, cfg)[0]
        else:
            place = settled(edges, {v: hashed(v) for v in near}, cfg)[0]
        want.append((n, cut_of(edges, place), len(edges)))
    assert [tuple(r) for r in run(spark, f"w1_drift_{strategy}", "slice")] == want


def weeks_of(db):
    rows = db.execute(f"select distinct date_trunc('week', ts) w, least(src, dst) a, greatest(src, dst) b from ({o.CALL}) where src <> dst order by 1").fetchall()
    weeks = defaultdict(list)
    for w, a, b in rows:
        weeks[w].append((a, b))
    return [weeks[w] for w in sorted(weeks)]


def test_weeks(spark, db):
    place, want = {}, []
    for n, edges in enumerate(weeks_of(db)):
        near = near_of(edges)
        place = settled(edges, {v: place.get(v, hashed(v)) for v in near}, MigrationConfig())[0]
        want.append((n, cut_of(edges, place), len(edges)))
    assert [tuple(r) for r in run(spark, "w7_cuts_weekly_adaptive", "week")] == want


def largest_clique(v, near, found):
    """The two-superstep search at v: the largest list that comes from all its other members; lists of higher vertices only."""
    lists = Counter()
    for j in near[v]:
        if j > v:
            common = {x for x in near[v] if x > v} & near[j]
            lists[tuple(sorted(common | {v, j}))] += 1
    sizes = [len(x) for x, n in lists.items() if n == len(x) - 1]
    return max([1, *(2 for j in near[v] if j > v), *sizes])


@pytest.mark.parametrize("arm", ["adaptive", "static"])
def test_clique_weeks(spark, db, arm):
    place, want, t = {}, [], 0
    for n, edges in enumerate(weeks_of(db)):
        near = near_of(edges)
        place = {v: place.get(v, hashed(v)) for v in near}
        cfg = MigrationConfig(adaptive=arm == "adaptive")
        vid = np.array(sorted(place))
        one = replicas.Replica(np.array([a for a, _ in edges]), np.array([b for _, b in edges]), vid, np.array([place[v] for v in vid]), cfg)
        one.t = t
        for _ in range(2):
            t += 1
            moved = one.step()
            place = dict(zip(vid.tolist(), one.part.tolist()))
            sizes = [largest_clique(v, near, None) for v in near] if t % 2 == 0 else []
            want.append((n, t, moved, cut_of(edges, place), len(edges), sum(s > 2 for s in sizes), max(sizes, default=None)))
    assert [tuple(r) for r in run(spark, f"w7_clique_weeks_{arm}", "superstep")] == want


def border(edges, inert, n):
    near = near_of(edges)
    live = {x for v in inert for x in near[v]} - inert
    ends = sorted((v, x) for v in live for x in near[v])
    first = max(b for _, b in edges) + 1
    return {(ends[mixed(v, 0, PICK, 2, j) % len(ends)][0], v) for v in range(first, first + n) for j in range(3)}


@pytest.mark.parametrize("arm", ["adaptive", "static"])
def test_expanded_tissue(spark, db, arm):
    edges = edges_of(db, "lattice")
    near = near_of(edges)
    side = round(len(near) ** (1 / 3))
    inert = {v for v in near if v % side + v // side % side + v // side**2 < 3}
    assert {tuple(r) for r in run(spark, "border_growth")} == border(edges, inert, 100)
    cfg = MigrationConfig(adaptive=arm == "adaptive")
    place = settled(edges, {v: hashed(v) for v in near}, cfg)[0]
    grown = sorted(set(edges) | border(edges, inert, max(1, len(near) // 10)))
    place, rows = settled(grown, {v: place.get(v, hashed(v)) for v in near_of(grown)}, cfg)
    got = run(spark, f"w8_expand_{arm}", "iteration")
    assert [(r.iteration, r["cut"], r.edges, r.moved) for r in got] == [(r[0], r[5], r[6], r[4]) for r in rows] and all(r.quiet for r in got)


def fire(edges, n, p, depth, seed=0):
    near = near_of(edges)
    known = sorted(near)
    out = set()
    for w in range(known[-1] + 1, known[-1] + 1 + n):
        start = known[mixed(w, seed, PICK) % len(known)]
        burnt, front = {start}, {start}
        for _ in range(depth):
            front = {x for v in front for x in near[v] if mixed_salted(x, w * 31 + seed * 7919 + BURN * 15485863) < p * 2**32} - burnt
            burnt |= front
        out |= {(v, w) for v in burnt}
    return out


def mixed_salted(x, salt):
    from graphdrift.functions.hashing import FACTOR, MASK

    v = (((x ^ (x >> 32)) & MASK) + salt) & MASK
    for _ in range(2):
        v = ((v >> 16 ^ v) * FACTOR) & MASK
    return v >> 16 ^ v


def test_forest_fire(spark, db):
    edges = edges_of(db, "cop")
    assert {tuple(r) for r in run(spark, "forest_fire_burst")} == fire(edges, 50, 0.3, 2)


@pytest.mark.parametrize("strategy", ["hash", "random", "dgr"])
def test_newcomers(spark, db, strategy):
    edges = edges_of(db, "cop")
    old = [e for e in edges if e[0] % 10 and e[1] % 10]
    base = settled(old, {v: hashed(v) for v in near_of(old)}, MigrationConfig())[0]
    near = near_of(edges)
    new = [v for v in near if v not in base]
    if strategy == "random":
        order = {v: i for i, v in enumerate(sorted(new, key=lambda v: (hashed(v, 2**40), v)))}
        place = base | {v: i % K for v, i in order.items()}
    else:
        place = base | {v: hashed(v) if strategy == "hash" else greedy(v, near, base) for v in new}
    rows = settled(edges, place, MigrationConfig())[1]
    got = newcomer_rows(spark)[strategy]
    last = max((r[0] for r in rows if r[4]), default=0)
    assert (got.cut_before, got.cut_after, got.edges, got.last_move) == (cut_of(edges, place), rows[-1][5], len(edges), last)


_rows = {}


def newcomer_rows(spark):
    if not _rows:
        _rows.update({r.strategy: r for r in run(spark, "w12_newcomers")})
    return _rows


def levels(near, root):
    seen, front, depth = {root: 0}, [root], 0
    while front:
        front = [x for x in {y for v in front for y in near[v]} if x not in seen]
        depth += bool(front)
        seen |= dict.fromkeys(front, depth)
    return seen


def test_diameters(spark, db):
    edges = edges_of(db, "pagelinks")
    near = near_of(edges)
    first = levels(near, min(a for a, _ in edges))
    far = min(v for v, d in first.items() if d == max(first.values()))
    assert tuple(run(spark, "diameter_sweep")[0]) == (max(levels(near, far).values()), far)
    exact = max(max(levels(near, v).values()) for v in near)
    assert run(spark, "diameter_sketch")[0].diameter == exact


def test_cliques_found_and_hot_zones(spark, db):
    edges = edges_of(db, "succession")
    near = near_of(edges)
    volume, place = Counter(), {v: hashed(v) for v in near}
    for v in near:
        volume[place[v]] += sum(len(near[j]) for j in near[v])
    assert {r.part: r.list_items for r in run(spark, "hot_zones")} == dict(volume)

    knn = registry.queries()["knn_edges"](spark, SF).collect()
    near = near_of([tuple(r) for r in knn])

    def exact(v):
        best = 1

        def grow(size, left):
            nonlocal best
            best = max(best, size)
            for x in sorted(left):
                grow(size + 1, {y for y in left if y > x} & near[x])

        grow(1, near[v])
        return best

    def heuristic(v):
        lists = Counter(tuple(sorted((near[v] & near[j]) | {v, j})) for j in near[v])
        return max([2 if near[v] else 1, *(len(x) for x, n in lists.items() if n == len(x) - 1)])

    (got,) = run(spark, "clique_hit_rate")
    assert (got.hits, got.vertices) == (sum(heuristic(v) == exact(v) for v in near), len(near))


def test_labels_until_stable(spark):
    pairs = [(1, 2), (2, 3), (3, 4), (4, 5), (10, 11), (11, 12), (5, 6)]
    edges = spark.createDataFrame(pairs, "src long, dst long")
    seeds = spark.createDataFrame([(1, 0), (6, 1), (10, 2), *[(v, None) for v in (2, 3, 4, 5, 11, 12)]], "vid long, label int")
    got = {r.vid: r.label for r in label_propagation(symmetric(edges), seeds, None).collect()}
    near, now, seen = near_of(pairs), {1: 0, 6: 1, 10: 2}, []
    while True:
        new = {}
        for v in near:
            count = Counter(now[x] for x in near[v] if x in now)
            new[v] = {1: 0, 6: 1, 10: 2}.get(v, min(count, key=lambda p: (-count[p], p)) if count else now.get(v))
        now = {v: p for v, p in new.items() if p is not None}
        if now in seen[-2:]:
            break
        seen.append(now)
    assert got == now


def test_bursts_at_a_small_scale(spark, db):
    rows = workloads.bursts(spark, SF, "pagelinks", (0.1,), 3).orderBy("phase", "iteration").collect()
    edges = edges_of(db, "pagelinks")
    place, want = {v: hashed(v) for v in near_of(edges)}, []
    for phase in range(2):
        if phase:
            edges = sorted(set(edges) | fire(edges, max(1, int(len(place) * 0.1)), 0.35, 3, 1))
            place = {v: place.get(v, hashed(v)) for v in near_of(edges)}
        place, told = settled(edges, place, MigrationConfig(), 3)
        want += [(phase, r[0], r[4], r[5], r[6], r[9], r[10]) for r in told]
    assert [(r.phase, r.iteration, r.moved, r["cut"], r.edges, r.messages, r.remote) for r in rows] == want
